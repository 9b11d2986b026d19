"""JVM-side column functions of the partitioner; nothing here needs Python on the executors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

MODULUS = 2_147_483_647


def scramble(x: Column | str, seed: int = 0) -> Column:
    """A hash of dense ids (below 2^31) for random orders and ties, the same in any SQL engine."""
    column = F.col(x) if isinstance(x, str) else x
    return (column.cast("long") * 48271 + seed) % MODULUS


def scramble_wide(x: Column | str, seed: int = 0) -> Column:
    """The same for ids of any size, where no other engine must agree."""
    return F.xxhash64(x, F.lit(seed))


def zigzag(x: Column) -> Column:
    """Signed to unsigned: 0, -1, 1, -2 become 0, 1, 2, 3."""
    return F.when(x >= 0, x * 2).otherwise(-2 * x - 1)


def unzigzag(x: Column) -> Column:
    return F.when(x % 2 == 0, F.shiftright(x, 1)).otherwise(-F.shiftright(x, 1) - 1)


def varint_len(x: Column) -> Column:
    """Bytes of a non-negative number with seven bits in each."""
    size = F.lit(1)
    for n in range(1, 9):
        size = size + (x >= F.lit(1 << (7 * n))).cast("int")
    return size


def entry_width(u: Column) -> Column:
    """Bits of a gain table's entry that holds values up to u: the smallest of 8, 16, 32, 64 that suffices."""
    return F.when(u < 1 << 8, 8).when(u < 1 << 16, 16).when(u < 1 << 32, 32).otherwise(64)


def next_power_of_two(x: Column) -> Column:
    """The smallest power of two that is at least x, 1 for x < 1."""
    out = F.lit(1).cast("long")
    for n in range(0, 40):
        out = F.when(x > F.lit(1 << n), F.lit(1 << (n + 1)).cast("long")).otherwise(out)
    return out


def running_sum(rows: DataFrame, by: list[str], order: str, value: Column, name: str, width: int = 65_536) -> DataFrame:
    """rows with the sum of value over the rows of the same `by` up to and including each, in the order of a dense number: sums of
    ranges of the order give what comes before a range, so that no window has more than `width` rows of a group."""
    ranged = rows.withColumn("_range", F.floor(F.col(order) / width)).withColumn("_value", value)
    sums = ranged.groupBy(*by, "_range").agg(F.sum("_value").alias("_sum"))
    # a row for each range of a group
    before = sums.select(*by, "_range", (F.sum("_sum").over(Window.partitionBy(*by).orderBy("_range")) - F.col("_sum")).alias("_before"))
    within = Window.partitionBy(*by, "_range").orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    return ranged.withColumn(name, F.sum("_value").over(within)).join(before, [*by, "_range"]).withColumn(name, F.col(name) + F.col("_before")).drop("_range", "_value", "_before")


#: Parts into which the movers of one target are dealt before they are ordered.
ADMISSION_PARTS = 64


def admitted_within(moves: DataFrame, target: str, order: list, weight: str, room: Column, spread: Column, inclusive: bool = True) -> DataFrame:
    """Of the moves into (or out of) each target, in the order given, those whose running weight is within the room (inclusive), or
    begins below it (not inclusive).

    A target's moves are first cut short in parts by `spread`, a hash of theirs: what a part's own running weight puts beyond the room is beyond
    it in the whole order too, and what stays up to and including the first beyond it in each part is enough to put all that
    follow beyond it. So one window per target sees at most ADMISSION_PARTS times its room, however many wish to move.
    """
    part = spread % ADMISSION_PARTS
    short = Window.partitionBy(target, "_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy(target).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    gone = lambda line: F.coalesce(F.sum(weight).over(line), F.lit(0))
    fits = (lambda run: run <= F.col("_room")) if inclusive else (lambda run: run < F.col("_room"))
    first = moves.withColumn("_room", room).withColumn("_part", part).withColumn("_gone", gone(short)).where(fits(F.col("_gone")))
    ran = first.withColumn("_gone", gone(whole))
    return ran.where(fits(F.col("_gone") + F.col(weight)) if inclusive else fits(F.col("_gone"))).drop("_room", "_part", "_gone")
