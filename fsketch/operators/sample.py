"""Uniform subsamples without replacement, by hash order: the same rows whatever the partitioning.

Hashes are uniform, so the b rows of least hash lie below a threshold that hardly more rows pass. Tasks drop the others
before anything is sorted or shuffled: what moves follows b, not the number of rows or of tasks. Where too few pass (row keys that
repeat spoil the uniformity) all rows are ordered instead, so the result is exact.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import uniform


def _keyed(df: DataFrame, seed: int, *tag) -> DataFrame:
    return df.withColumn("_h", uniform("s", seed, *tag, F.col("row_key")))


def threshold(b: int, n: int) -> float:
    """Below it lie b of n uniforms at least, but for a chance of some 1e-15."""
    return min(1.0, (b + 8 * math.sqrt(b) + 40) / max(n, 1))


def _least(keyed: DataFrame, b: int, n: int | None) -> DataFrame:
    """Few rows that hold the b of least hash; all of them where that cannot be told."""
    n = keyed.count() if n is None else n
    if threshold(b, n) >= 1:
        return keyed
    few = keyed.where(F.col("_h") < threshold(b, n))
    return few if few.count() >= min(b, n) else keyed


def shared(df: DataFrame, b: int, seed: int = 42, n: int | None = None) -> DataFrame:
    """b rows of least hash (all rows if there are fewer). ``n``, the number of rows, saves counting them."""
    return _least(_keyed(df, seed), b, n).orderBy("_h", "row_key").limit(b).drop("_h")


def per_frequency(df: DataFrame, b: int, m: int, seed: int = 42, independent: bool | None = None, n: int | None = None) -> DataFrame:
    """Rows with j (0 to m - 1) and pos (0 to b - 1): a subsample of b rows for each frequency.

    The first m b rows in hash order are dealt out in blocks, each of which is a uniform subsample by itself.
    ``independent`` hashes again for every j instead; that is also done where the table has under m b rows.
    """
    n = df.count() if n is None else n
    if independent is None:
        independent = n < m * b
    if independent:
        each = _every_frequency(df, m, seed)
        return _ranked(each, b, ["j"], F.lit(threshold(b, n))) if _enough(each, b, ["j"], F.lit(threshold(b, n)), m, {None: n}) else _ranked(each, b, ["j"])
    first = _least(_keyed(df, seed), m * b, n).orderBy("_h", "row_key").limit(m * b)
    rank = F.row_number().over(Window.orderBy("_h", "row_key")) - 1  # over m b rows, whatever the table's size
    return first.withColumn("_r", rank).withColumn("j", F.expr(f"cast(_r div {b} as int)")).withColumn("pos", F.col("_r") % b).drop("_h", "_r")


def _every_frequency(df: DataFrame, m: int, seed: int) -> DataFrame:
    """Each row m times, with a hash of its own for every j."""
    return _keyed(df.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(m - 1)))), seed, F.col("j"))


def _ranked(keyed: DataFrame, b: int, by: list[str], below: Column | None = None) -> DataFrame:
    few = keyed if below is None else keyed.where(F.col("_h") < below)
    ranked = few.withColumn("pos", F.row_number().over(Window.partitionBy(*by).orderBy("_h", "row_key"))).where(F.col("pos") <= b)
    return ranked.withColumn("pos", F.col("pos") - 1).drop("_h")


def _enough(keyed: DataFrame, b: int, by: list[str], below: Column, parts: int, sizes: dict) -> bool:
    """Whether all parts have min(b, size) rows below; a part is missing only if it has none."""
    got = keyed.where(F.col("_h") < below).groupBy(*by).count().collect()
    least = lambda r: min(b, sizes.get(None) or sizes[r[by[0]]])
    return len(got) == parts and all(r["count"] >= least(r) for r in got)


def sizes_of(assigned: DataFrame, by: str = "g") -> dict:
    """Rows per group, on the driver: one number per group."""
    return {r[0]: r[1] for r in assigned.groupBy(by).count().collect()}


def group_threshold(b: int, sizes: dict, by: str = "g") -> Column:
    """The threshold of a row's group, as literals: one per group."""
    at = F.lit(1.0)
    for g, n in sizes.items():
        at = F.when(F.col(by) == g, threshold(b, n)).otherwise(at)
    return at


def per_group(assigned: DataFrame, b: int, seed: int = 42, by: str = "g", sizes: dict | None = None, sure: bool = False) -> DataFrame:
    """min(b, group size) rows of each group; tasks drop the rows above a group's threshold before anything is shuffled.

    ``sizes`` (rows per group) saves a count, ``sure`` the look at whether enough rows pass: the caller then checks what it gets.
    """
    keyed, sizes = _keyed(assigned, seed), sizes_of(assigned, by) if sizes is None else sizes
    below = group_threshold(b, sizes, by)
    return _ranked(keyed, b, [by], below if sure or _enough(keyed, b, [by], below, len(sizes), sizes) else None)


def per_group_frequency(assigned: DataFrame, b: int, m: int, seed: int = 42, by: str = "g", sizes: dict | None = None, sure: bool = False) -> DataFrame:
    """Rows with j and pos: of each group a subsample of min(b, size) rows for each of m frequencies.

    Dealt out of a group's first m b rows in blocks, as in ``per_frequency``; where a group has fewer, all groups are hashed again
    for every j.
    """
    sizes = sizes_of(assigned, by) if sizes is None else sizes
    if all(n >= m * b for n in sizes.values()):
        first = per_group(assigned, m * b, seed, by, sizes, sure)
        return first.withColumn("j", F.expr(f"cast(pos div {b} as int)")).withColumn("pos", F.col("pos") % b)
    each, below = _every_frequency(assigned, m, seed), group_threshold(b, sizes, by)
    enough = sure or _enough(each, b, [by, "j"], below, len(sizes) * m, sizes)
    return _ranked(each, b, [by, "j"], below if enough else None)
