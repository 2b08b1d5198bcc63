"""Minimax contiguous sharding [native].

Documents are ordered by the 64-bit hash of their text; documents of equal text form one atomic group. The smallest
capacity C for which a greedy left-to-right fill needs at most ``n_shards`` shards is found by binary search, and the
order is cut where that fill cuts.

The driver never sees groups one by one. It holds the order as buckets of the hash (4,096 at first) with their byte
sums. A bucket taken as indivisible gives an upper bound of C, one taken as divisible a lower bound; only buckets
into which a cut of either bound may fall are split 256 ways, until both bounds meet, so C is exact.

Defined results: null text counts as the empty text; an empty table gives an empty result; repeated rows are rows of
the same group; further columns of the input are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut_lineage

FIRST_SHIFT, FAN_BITS = 52, 8
ROWS_PER_UNIT = 100_000


def _positions(items: list[tuple], ends: list[int], capacity: int, divisible: bool, most: int) -> list[int] | None:
    """Ends (in bytes) of a greedy fill with at most ``most`` shards; None if they don't suffice."""
    from bisect import bisect_right

    total, start, cuts = ends[-1], 0, []
    while start < total:
        if len(cuts) == most:
            return None
        reach = start + capacity
        if reach >= total:
            end = total
        else:
            i = bisect_right(ends, reach)
            before = ends[i - 1] if i else 0
            end = reach if divisible and items[i][4] > 1 else before
        if end <= start:
            return None
        cuts.append(end)
        start = end
    return cuts


def _smallest(items: list[tuple], ends: list[int], low: int, most: int, divisible: bool) -> int:
    high = max(low, ends[-1])
    while low < high:
        mid = (low + high) // 2
        if _positions(items, ends, mid, divisible, most) is None:
            low = mid + 1
        else:
            high = mid
    return low


def _ends(items: list[tuple]) -> list[int]:
    from itertools import accumulate

    return list(accumulate(x[2] for x in items))


def find_cuts(groups: DataFrame, n_shards: int) -> tuple[list[int], int]:
    """(first hash of shards 1.., smallest capacity) for ``groups`` (h, bytes), one row per atomic group."""

    def buckets(df: DataFrame, shift: int) -> list[tuple]:
        key = F.shiftright("h", shift) if shift else F.col("h")
        rows = df.groupBy(key.alias("b")).agg(F.sum("bytes").alias("s"), F.max("bytes").alias("m"), F.count("*").alias("n")).collect()
        return [(r.b, shift, r.s, r.m, r.n) for r in rows]

    items = sorted(buckets(groups, FIRST_SHIFT), key=lambda x: x[0] << x[1])
    if not items:
        return [], 0
    floor = max(max(x[3] for x in items), -(-sum(x[2] for x in items) // n_shards))
    while True:
        ends = _ends(items)
        low = _smallest(items, ends, floor, n_shards, True)
        high = _smallest(items, ends, floor, n_shards, False)
        if low == high:
            break
        marks = [_positions(items, ends, low, True, n_shards), _positions(items, ends, high, True, n_shards), _positions(items, ends, high, False, n_shards)]
        split: set[int] = set()
        begin = 0
        for j in range(n_shards):
            at = [m[j] for m in marks if m and j < len(m)]
            if at:
                for i, x in enumerate(items):
                    begin = ends[i] - x[2]
                    if x[4] > 1 and begin <= max(at) and ends[i] >= min(at):
                        split.add(i)
        by_shift: dict[int, list[int]] = {}
        for i in split:
            by_shift.setdefault(items[i][1], []).append(items[i][0])
        kept = [x for i, x in enumerate(items) if i not in split]
        for shift, ids in by_shift.items():
            kept += buckets(groups.where(F.shiftright("h", shift).isin(ids)), max(0, shift - FAN_BITS))
        items = sorted(kept, key=lambda x: x[0] << x[1])
    cuts = _positions(items, ends, high, False, n_shards) or []
    at = {end - x[2]: x for x, end in zip(items, ends, strict=True)}
    return [at[c][0] << at[c][1] for c in cuts[:-1]], high


def shard_documents(docs: DataFrame, n_shards: int = 24, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard): law ``bytes``, slots gapless within each shard."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = cut_lineage(
        docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text).cast("long") + 8).alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("h"))
    )
    groups = rows.groupBy("h").agg(F.sum("size").alias("bytes"))
    cuts, _ = find_cuts(groups, n_shards)
    shard = F.lit(0)
    for c in cuts:
        shard = shard + (F.col("h") >= F.lit(c)).cast("int")
    units = max(8, -(-rows.count() // ROWS_PER_UNIT))
    placed = rows.select("doc_id", "size", "text_crc32", shard.alias("shard"), F.pmod(F.xxhash64("doc_id", "h"), F.lit(units)).alias("unit"))
    counts = placed.groupBy("shard", "unit").agg(F.count("*").alias("n"))
    w = Window.partitionBy("shard").orderBy("unit")
    offsets = counts.select("shard", "unit", (F.sum("n").over(w) - F.col("n")).alias("offset"))
    ranked = placed.withColumn("at", F.row_number().over(Window.partitionBy("shard", "unit").orderBy("doc_id", "text_crc32")))
    return ranked.join(offsets, ["shard", "unit"]).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("offset") + F.col("at") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
