"""The methods: cleaning, coding, clustering, contraction, initial partitions, refinement, measures, baselines."""
