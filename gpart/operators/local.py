"""Solvers for graphs that fit one task: growing, two-way and k-way local search, recursive bisection, matching hierarchies.

Used on the coarsest level and in the tasks of localised search. Graphs are adjacency lists of (neighbour, weight).
"""

from __future__ import annotations

import random
from collections import deque
from collections.abc import Sequence
from dataclasses import dataclass
from heapq import heappop, heappush

from gpart.operators.probe import ProbeTable

Adjacency = list[list[tuple[int, int]]]


@dataclass
class LocalGraph:
    weights: list[int]
    adjacent: Adjacency

    @staticmethod
    def of(n: int, weights: Sequence[int], edges: Sequence[tuple[int, int, int]]) -> LocalGraph:
        """edges: (src, dst, w), both directions."""
        adjacent: Adjacency = [[] for _ in range(n)]
        for a, b, w in edges:
            adjacent[a].append((b, w))
        return LocalGraph(list(weights), adjacent)

    @staticmethod
    def of_arrays(arrays: tuple) -> LocalGraph:
        """From arrays (weights, src, dst, w), edges by rising source."""
        weights, src, dst, w = (a.tolist() for a in arrays)
        adjacent: Adjacency = [[] for _ in weights]
        for a, b, x in zip(src, dst, w, strict=True):
            adjacent[a].append((b, x))
        return LocalGraph(weights, adjacent)

    def part(self, vertices: list[int]) -> LocalGraph:
        place = {v: i for i, v in enumerate(vertices)}
        return LocalGraph([self.weights[v] for v in vertices], [[(place[u], w) for u, w in self.adjacent[v] if u in place] for v in vertices])

    def cut(self, blocks: Sequence[int]) -> int:
        return sum(w for v, near in enumerate(self.adjacent) for u, w in near if v < u and blocks[v] != blocks[u])

    def loads(self, blocks: Sequence[int], k: int) -> list[int]:
        out = [0] * k
        for b, w in zip(blocks, self.weights, strict=True):
            out[b] += w
        return out


def grow(g: LocalGraph, target: int, method: str, rng: random.Random) -> list[int]:
    """A bipartition: block 0 grows from a random vertex until it weighs `target`; a used-up component is followed by another start.

    methods: 'bfs' by distance, 'greedy' by the weight of edges into the block less the others', 'random'.
    """
    n = len(g.weights)
    blocks, load = [1] * n, 0
    order = list(range(n))
    rng.shuffle(order)
    if method == "random":
        for v in order:
            if load + g.weights[v] <= target:
                blocks[v], load = 0, load + g.weights[v]
        return blocks
    waiting: deque[int] = deque()
    heap: list[tuple[int, int, int]] = []
    gain = [0] * n
    queued = [False] * n
    starts = iter(order)
    while load < target:
        if method == "bfs":
            v = waiting.popleft() if waiting else next((x for x in starts if blocks[x] and not queued[x]), None)
        else:
            v = None
            while heap and v is None:
                value, _, x = heappop(heap)
                v = x if blocks[x] and -value == gain[x] else None
            if v is None:
                v = next((x for x in starts if blocks[x]), None)
        if v is None:
            break
        queued[v] = True
        if load + g.weights[v] > target and load:
            if method == "bfs" or not heap:
                break
            continue
        blocks[v], load = 0, load + g.weights[v]
        for u, w in g.adjacent[v]:
            if blocks[u]:
                if method == "bfs":
                    if not queued[u]:
                        queued[u] = True
                        waiting.append(u)
                else:
                    gain[u] += 2 * w if queued[u] else w
                    queued[u] = True
                    heappush(heap, (-gain[u], rng.randrange(1 << 20), u))
    return blocks


class RowTable:
    """Affinities in a row with an entry for each block."""

    def __init__(self, k: int):
        self.values = [0] * k

    def add(self, block: int, delta: int) -> None:
        self.values[block] += delta

    def items(self) -> dict[int, int]:
        return {b: a for b, a in enumerate(self.values) if a}


def affinities_of(g: LocalGraph, blocks: Sequence[int], v: int, k: int, table: str) -> RowTable | ProbeTable:
    near = g.adjacent[v]
    out = RowTable(k) if table == "full" or len(near) > k else ProbeTable(len(near), sum(w for _, w in near))
    for u, w in near:
        out.add(blocks[u], w)
    return out


def search(g: LocalGraph, blocks: list[int], caps: list[int], seeds: Sequence[int], rng: random.Random, patience: int = 200, once: set[int] | None = None, table: str = "map") -> list[tuple[int, int, int]]:
    """Localised search: moves (vertex, from, to), best first from the seeds outward, losses too, each vertex at most once; what
    comes after the best prefix is undone. blocks changes to the result. On the way a block may be too heavy by one vertex, else
    full blocks could never exchange vertices; a prefix with fewer blocks too heavy is better than any other.

    table: how the affinities of a vertex that has been looked at are held: `map` in a dictionary, `full` in a row of k entries,
    `hybrid` in such a row or, with at most k edges, in a small probing table, `none` not at all. All give the same moves."""
    k = len(caps)
    heaviest = max((g.weights[v] for v in range(len(g.weights)) if once is None or v not in once), default=0)
    rooms = [c + heaviest for c in caps]
    loads = g.loads(blocks, k)
    moved = set() if once is None else once
    stamp: dict[int, int] = {}
    heap: list[tuple[int, int, int, int, int]] = []
    adjacent, weights, bits = g.adjacent, g.weights, rng.getrandbits
    plain = table not in ("full", "hybrid")
    held: dict[int, dict[int, int] | RowTable | ProbeTable] = {}

    def push(v: int) -> None:  # called for every edge of what moves, so it calls little itself
        found = held.get(v)
        if found is None:
            if plain:
                found = {}
                for u, w in adjacent[v]:
                    b = blocks[u]
                    found[b] = found[b] + w if b in found else w
            else:
                found = affinities_of(g, blocks, v, k, table)
            if table != "none":
                held[v] = found
        inside = found if plain else found.items()
        own, weight = blocks[v], weights[v]
        kept = inside.get(own, 0)
        best = None
        for b, a in inside.items():
            if b != own and a and loads[b] + weight <= rooms[b]:
                fit = (a - kept, -loads[b], b)
                if best is None or fit > best:
                    best = fit
        if loads[own] > caps[own]:
            light = min(range(k), key=loads.__getitem__)
            if light != own and loads[light] + weight <= caps[light]:
                fit = (inside.get(light, 0) - kept, -loads[light], light)
                if best is None or fit > best:
                    best = fit
        stamp[v] = turn = stamp.get(v, 0) + 1
        if best is not None:
            tie = bits(21)
            while tie >= 1 << 20:
                tie = bits(21)
            heappush(heap, (-best[0], tie, v, best[2], turn))

    for v in seeds:
        if v not in moved:
            push(v)
    log: list[tuple[int, int, int]] = []
    total = best = 0
    over = sum(x > c for x, c in zip(loads, caps, strict=True))
    best_over, best_at, idle = over, 0, 0
    while heap and idle < patience:
        value, _, v, to, when = heappop(heap)
        if v in moved or stamp[v] != when:
            continue
        if loads[to] + g.weights[v] > rooms[to]:
            push(v)
            if stamp[v] > 50:
                moved.add(v)
            continue
        own = blocks[v]
        over -= (loads[own] > caps[own]) + (loads[to] > caps[to])
        loads[own] -= g.weights[v]
        loads[to] += g.weights[v]
        over += (loads[own] > caps[own]) + (loads[to] > caps[to])
        blocks[v] = to
        moved.add(v)
        log.append((v, own, to))
        total -= value
        if (over, -total) < (best_over, -best):
            best_over, best, best_at, idle = over, total, len(log), 0
        else:
            idle += 1
        for u, w in adjacent[v]:
            if (found := held.get(u)) is not None:
                if plain:
                    found[own] = found.get(own, 0) - w
                    found[to] = found.get(to, 0) + w
                else:
                    found.add(own, -w)
                    found.add(to, w)
            if u not in moved:
                push(u)
    for v, own, _ in reversed(log[best_at:]):
        blocks[v] = own
    return log[:best_at]


def boundary(g: LocalGraph, blocks: Sequence[int]) -> list[int]:
    out = []
    for v, near in enumerate(g.adjacent):
        own = blocks[v]
        for u, _ in near:
            if blocks[u] != own:
                out.append(v)
                break
    return out


def improve(g: LocalGraph, blocks: list[int], caps: list[int], rng: random.Random, rounds: int = 4) -> list[int]:
    """Rounds of search from the whole boundary, while they help; from anywhere where a block is too heavy."""
    for _ in range(rounds):
        loads = g.loads(blocks, len(caps))
        heavy = {b for b, (x, c) in enumerate(zip(loads, caps, strict=True)) if x > c}
        seeds = boundary(g, blocks) + [v for v, b in enumerate(blocks) if b in heavy]
        rng.shuffle(seeds)
        if not search(g, blocks, caps, seeds, rng):
            break
    return blocks


def match(g: LocalGraph, rng: random.Random, cap: int) -> tuple[LocalGraph, list[int]]:
    """Heavy-edge matching: the coarse graph and each vertex's coarse one."""
    n = len(g.weights)
    coarse = [-1] * n
    order = list(range(n))
    rng.shuffle(order)
    count = 0
    for v in order:
        if coarse[v] < 0:
            free = [(w, -g.weights[u], u) for u, w in g.adjacent[v] if coarse[u] < 0 and g.weights[u] + g.weights[v] <= cap]
            coarse[v] = count
            if free:
                coarse[max(free)[2]] = count
            count += 1
    return g_contract(g, coarse, count), coarse


def g_contract(g: LocalGraph, coarse: list[int], count: int) -> LocalGraph:
    weights = [0] * count
    sums: list[dict[int, int]] = [{} for _ in range(count)]
    for v, near in enumerate(g.adjacent):
        a = coarse[v]
        weights[a] += g.weights[v]
        own = sums[a]
        for u, w in near:
            if (b := coarse[u]) != a:
                own[b] = own.get(b, 0) + w
    return LocalGraph(weights, [list(x.items()) for x in sums])


METHODS = ("bfs", "greedy", "random")


def bipartition(g: LocalGraph, target: int, caps: list[int], rng: random.Random, tries: int = 4, methods: Sequence[str] = METHODS) -> list[int]:
    """The best of a portfolio of growings with local search, on the coarsest graph of a small hierarchy of its own."""
    if len(g.weights) > 240:
        small, coarse = match(g, rng, max(1, sum(g.weights) // 60))
        if len(small.weights) < 0.95 * len(g.weights):
            inner = bipartition(small, target, caps, rng, tries, methods)
            return improve(g, [inner[c] for c in coarse], caps, rng, 2)
    best: tuple[tuple[int, int], list[int]] | None = None
    for i in range(tries):
        for method in methods:
            blocks = improve(g, grow(g, target, method, rng), caps, rng, 2)
            loads = g.loads(blocks, 2)
            score = (sum(max(0, x - c) for x, c in zip(loads, caps, strict=True)), g.cut(blocks))
            if best is None or score < best[0]:
                best = (score, blocks)
    return best[1] if best else []


def bisect(g: LocalGraph, k: int, cap: int, rng: random.Random, tries: int = 4, methods: Sequence[str] = METHODS) -> list[int]:
    """k blocks by recursive bisection; the halves carry as many final blocks as they will be split into, and a side may weigh
    what its blocks may, less what the recursion below still needs as slack."""
    if k == 1 or not g.weights:
        return [0] * len(g.weights)
    left = (k + 1) // 2
    total = sum(g.weights)
    slack = max(0.0, cap * k / total - 1) / max(1, (k - 1).bit_length()) if total else 0
    caps = [max(-(-total * share // k), min(cap * share, int((1 + slack) * total * share / k))) for share in (left, k - left)]
    sides = bipartition(g, total * left // k, caps, rng, tries, methods)
    out = [0] * len(sides)
    for side, share, offset in ((0, left, 0), (1, k - left, left)):
        own = [v for v, s in enumerate(sides) if s == side]
        for v, b in zip(own, bisect(g.part(own), share, cap, rng, tries, methods), strict=True):
            out[v] = b + offset
    return out


def propagate(g: LocalGraph, labels: list[int], loads: dict[int, int], cap: int, rng: random.Random, rounds: int) -> list[int]:
    """Label propagation one vertex after another: the best-rated label with room, its own on ties."""
    order, adjacent, weights = list(range(len(labels))), g.adjacent, g.weights
    for _ in range(rounds):
        rng.shuffle(order)
        moved = 0
        for v in order:
            own, weight = labels[v], weights[v]
            sums: dict[int, int] = {}
            for u, w in adjacent[v]:
                label = labels[u]
                sums[label] = sums[label] + w if label in sums else w
            best, value = own, sums.get(own, 0)
            for label, w in sums.items():
                if w > value and loads.get(label, 0) + weight <= cap:
                    best, value = label, w
            if best != own:
                labels[v] = best
                loads[own] -= weight
                loads[best] = loads.get(best, 0) + weight
                moved += 1
        if not moved:
            break
    return labels


def cluster(g: LocalGraph, cap: int, rng: random.Random, rounds: int = 5) -> tuple[LocalGraph, list[int]]:
    """Size-constrained clustering and its contraction: the coarse graph and each vertex's coarse one."""
    labels = propagate(g, list(range(len(g.weights))), dict(enumerate(g.weights)), cap, rng, rounds)
    place = {c: i for i, c in enumerate(sorted(set(labels)))}
    coarse = [place[c] for c in labels]
    return g_contract(g, coarse, len(place)), coarse


def solve(g: LocalGraph, k: int, cap: int, seed: int, tries: int = 4, methods: Sequence[str] = METHODS, limit: int = 30, fm: bool = False) -> list[int]:
    """A k-way partition of a graph that fits one task: clusterings down to `limit` vertices for each block, recursive bisection,
    then label propagation and, on the coarsest graph (on all with fm), k-way search."""
    rng = random.Random(seed)
    if len(g.weights) > max(400, limit * k):
        small, coarse = cluster(g, max(1, cap // 12), rng)
        if len(small.weights) > 0.9 * len(g.weights):
            small, coarse = match(g, rng, max(2, cap // 6))
        if len(small.weights) <= 0.9 * len(g.weights):
            inner = solve(small, k, cap, seed, tries, methods, limit, fm)
            blocks = [inner[c] for c in coarse]
            blocks = propagate(g, blocks, dict(enumerate(g.loads(blocks, k))), cap, rng, 3)
            settled = not fm and max(g.loads(blocks, k)) <= cap
            return blocks if settled else improve(g, blocks, [cap] * k, rng, 2)
    return improve(g, bisect(g, k, cap, rng, tries, methods), [cap] * k, rng)
