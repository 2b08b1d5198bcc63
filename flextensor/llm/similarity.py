"""N-gram Jaccard self-join by vertical partitioning.

Distinct 5-word shingles, hashed to 64 bits, are put in one global order, and that order is cut into fragments. Each
fragment is counted on its own; partial counts are summed, first per document, then per pair.

1. Documents of equal sets become one node, known by a 64-bit digest of the set.
2. Two sets that reach the threshold share ``t`` of their first ``n - ceil(threshold n) + t`` shingles in any global
   order. In the order of the hash each fragment counts, per node, which of those another node has as well; nodes whose
   sum is under t for the smallest partner they may have are linked with nothing. Ordinary documents end here.
3. For the nodes left, fragments count in how many of them each shingle occurs. The global order is now: rare shingles
   first, in classes of twice the frequency, by hash within a class. The classes reach all tasks as an array of bounded
   size, one cell for many hashes, which holds the highest class of the cell; so the order is the same everywhere, and a
   shingle of class 0 is in one node only. Nodes with too few shingles of other classes end here.
4. Of nodes left, the shingles among the first ``n - ceil(threshold n) + 1`` that aren't of class 0 make the lists of
   candidates. Both shingles' places bound the overlap of a pair from its first common shingle on, and only pairs
   that can still reach the threshold are made: passages in many documents of their own give none.
5. In each list all nodes meet one centre; each node is held against the centre it meets most. Pairs are counted exactly:
   per fragment of the sets, then summed per pair. Connected components of these links follow.
6. Lists whose nodes are still in several components give the pairs across components, bounded and counted likewise: no
   link that could join two components is missed, and no pair inside one is ever made.

Defined results: null, empty and blank texts have no shingle and are their own component; repeated rows of one doc_id
and text are one document, rows of one doc_id with other texts are documents of their own; a null doc_id is never the
smallest of a component unless all are null; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import cut_lineage
from .common import mix, shingle_sets, slices, utf8

COUNT_ROWS = 2_000_000  # prefix shingles counted in one fragment
FRAGMENT_ROWS = 2_000_000  # shingles of kept sets counted in one fragment
CHUNK_ROWS = 1_000_000  # shingles a fragment takes in at a time
BROADCAST_NODES = 2_000_000
BROADCAST_PAIRS = 1_000_000
MOST_CELL_BITS = 27  # the array of classes has at most this many bits of address, a byte each
HOT_KEYS, HOT_LEAST = 50_000, 1_000  # keys of at least HOT_LEAST rows and a HOT_KEYS-th of all are broadcast: at most HOT_KEYS of them
BLOCK_ROWS = 20_000  # rows of one list in one block of a join
PREFIX_SPAN = 0.42  # prefixes of all but short texts end below this part of the hash range
SET_FRAGMENTS = 8


def shared_at_least(n, extra: float = 0.1):
    """t: shared shingles asked of a prefix of a set of n."""
    return np.maximum(1, np.floor(np.asarray(n) * extra)).astype(np.int64)


def least_overlap(n, percent: int = 75):
    """The least number of shingles of a set of n that any similar set has as well."""
    return (percent * np.asarray(n, np.int64) + 99) // 100


def prefix_length(n, percent: int = 75):
    n = np.asarray(n, np.int64)
    return np.minimum(n, n - least_overlap(n, percent) + shared_at_least(n))


def _digest(s: np.ndarray) -> int:
    with np.errstate(over="ignore"):
        return int(np.sum(mix(s * np.uint64(3) + np.uint64(1)), dtype=np.uint64).astype(np.int64)) if len(s) else 0


def shingle_table(docs: DataFrame, k: int) -> DataFrame:
    """(doc_id, text_key, n, digest) of ``docs`` (doc_id, text_key, text)"""

    def run(batches):
        for whole in batches:
            for b in slices(whole):
                sets = shingle_sets(*utf8(b.column(2)), k)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([len(s) for s in sets], pa.int64()), pa.array([_digest(s) for s in sets], pa.int64())], ["doc_id", "text_key", "n", "digest"])

    return docs.mapInArrow(run, "doc_id long, text_key long, n long, digest long")


# -- suspects: prefixes in the order of the hash ------------------------------------------------------------------------
def _fragment_rows(docs: DataFrame, k: int, percent: int, cuts: int) -> DataFrame:
    """(frag, hashes, told, counts, digests): prefix shingles of many documents by fragment. Shingles that several of them
    have are counted here, in rows of frag -1, and sent on once, marked as told."""

    def run(batches):
        for whole in batches:
            for b in slices(whole):
                sets = shingle_sets(*utf8(b.column(0)), k)
                digests = np.array([_digest(s) for s in sets], np.int64)
                _, once = np.unique(digests, return_index=True)
                n = np.array([len(s) for s in sets], np.int64)
                once = once[n[once] > 0]
                if not len(once):
                    continue
                take = prefix_length(n[once], percent)
                h, owner = np.concatenate([sets[i][:p] for i, p in zip(once, take, strict=True)]), np.repeat(once, take)
                order = np.argsort(h, kind="stable")
                h, owner = h[order], owner[order]
                at = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
                size = np.diff(np.r_[at, len(h)])
                here = np.bincount(owner[np.repeat(size > 1, size)], minlength=len(sets))
                h, owner, told = h[at], owner[at], (size > 1).astype(np.uint8)
                frag = np.minimum((h / 2.0**64 * (cuts / PREFIX_SPAN)).astype(np.int64), cuts - 1)
                order = np.lexsort((owner, frag))
                h, owner, told, frag = h[order], owner[order], told[order], frag[order]
                at = np.flatnonzero(np.r_[True, frag[1:] != frag[:-1]])
                some = np.flatnonzero(here)
                columns: list[list[bytes]] = [[b""], [b""], [here[some].astype(np.int32).tobytes()], [digests[some].tobytes()]]
                for x, y in zip(at, np.r_[at[1:], len(frag)], strict=True):
                    first = x + np.flatnonzero(np.r_[True, owner[x + 1 : y] != owner[x : y - 1]])
                    for col, v in zip(columns, (h[x:y], told[x:y], np.diff(np.r_[first, y]).astype(np.int32), digests[owner[first]]), strict=True):
                        col.append(v.tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(np.r_[-1, frag[at]].astype(np.int32)), *(pa.array(c, pa.binary()) for c in columns)], ["frag", "hashes", "told", "counts", "digests"])

    return docs.select("text").mapInArrow(run, "frag int, hashes binary, told binary, counts binary, digests binary")


def _chunks(frames: Iterator[pd.DataFrame], size_col: str, width: int) -> Iterator[tuple[int, pd.DataFrame]]:
    """(fragment, rows) of a partition sorted by fragment, about CHUNK_ROWS shingles at a time."""
    now, held, n = None, [], 0
    for pdf in frames:
        for r in pdf.itertuples(index=False):
            if held and (r.frag != now or n >= CHUNK_ROWS):
                yield now, pd.DataFrame(held)
                held, n = [], 0
            now = r.frag
            held.append(r)
            n += len(getattr(r, size_col)) // width
    if held:
        yield now, pd.DataFrame(held)


def _joined(col: pd.Series, kind) -> np.ndarray:
    return np.frombuffer(b"".join(col), kind)


def _shared_counts(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """(digest, shared): prefix shingles of a fragment that another digest has as well. A digest may be counted twice where
    its text is repeated, which only keeps it. Of earlier chunks one digest of each shingle is remembered."""
    now = None
    for frag, rows in _chunks(frames, "hashes", 8):
        digests, counts = _joined(rows["digests"], np.int64), _joined(rows["counts"], np.int32)
        if frag < 0:
            yield pd.DataFrame({"digest": digests, "shared": counts.astype(np.int64)})
            continue
        if frag != now:
            now, state = frag, (np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.uint8))
        h, d, told = (np.concatenate([a, b]) for a, b in zip(state, (_joined(rows["hashes"], np.uint64), np.repeat(digests, counts), _joined(rows["told"], np.uint8)), strict=True))
        order = np.lexsort((1 - told, d, h))
        h, d, told = h[order], d[order], told[order]
        new = np.r_[True, (h[1:] != h[:-1]) | (d[1:] != d[:-1])]
        h, d, told = h[new], d[new], told[new]
        at = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
        size = np.diff(np.r_[at, len(h)])
        u, c = np.unique(d[np.repeat(size > 1, size) & (told == 0)], return_counts=True)
        state = h[at], d[at], np.maximum(np.maximum.reduceat(told, at), size > 1).astype(np.uint8)
        yield pd.DataFrame({"digest": u, "shared": c.astype(np.int64)})


# -- the order by frequency ---------------------------------------------------------------------------------------------
def _kept_sets(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[tuple[np.ndarray, list[np.ndarray]]]:
    """(digests, sets) of rows (text, digest); a row whose text isn't the one of the digest is passed over."""
    for whole in batches:
        for b in slices(whole):
            sets, want = shingle_sets(*utf8(b.column(0)), k), b.column(1).to_numpy(zero_copy_only=False)
            good = [i for i, s in enumerate(sets) if len(s) and _digest(s) == want[i]]
            if good:
                yield want[good], [sets[i] for i in good]


def _classes(kept: DataFrame, k: int, cuts: int, cell_bits: int) -> np.ndarray:
    """The class of each cell of hashes: log2 of the number of nodes with the commonest shingle in it."""
    frag_bits = cuts.bit_length() - 1

    def send(batches):
        for _, sets in _kept_sets(batches, k):
            h, c = np.unique(np.concatenate(sets), return_counts=True)
            frag = (h >> np.uint64(64 - frag_bits)).astype(np.int64)
            at = np.flatnonzero(np.r_[True, frag[1:] != frag[:-1]])
            ends = np.r_[at[1:], len(h)]
            yield pa.RecordBatch.from_arrays([pa.array(frag[at].astype(np.int32)), *(pa.array([v[x:y].tobytes() for x, y in zip(at, ends, strict=True)], pa.binary()) for v in (h, c.astype(np.int32)))], ["frag", "hashes", "counts"])

    def count(frames):
        now, held = None, []

        def cells(h, c):
            out = np.zeros(1 << (cell_bits - frag_bits), np.uint8)
            where = ((h >> np.uint64(64 - cell_bits)) & np.uint64(len(out) - 1)).astype(np.int64)
            np.maximum.at(out, where, np.floor(np.log2(c)).astype(np.uint8))
            return pd.DataFrame({"frag": [now], "cells": [out.tobytes()]})

        for frag, rows in _chunks(frames, "hashes", 8):
            if frag != now:
                if now is not None:
                    yield cells(*held)
                now, held = frag, (np.zeros(0, np.uint64), np.zeros(0, np.int64))
            h, c = np.concatenate([held[0], _joined(rows["hashes"], np.uint64)]), np.concatenate([held[1], _joined(rows["counts"], np.int32)])
            order = np.argsort(h, kind="stable")
            h, c = h[order], c[order]
            at = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            held = h[at], np.add.reduceat(c, at)
        if now is not None:
            yield cells(*held)

    out = np.zeros(1 << cell_bits, np.uint8)
    width = len(out) // cuts
    by_frag = kept.mapInArrow(send, "frag int, hashes binary, counts binary").repartition("frag").sortWithinPartitions("frag")
    for r in by_frag.mapInPandas(count, "frag int, cells binary").collect():  # together as large as the array
        out[r.frag * width : (r.frag + 1) * width] = np.frombuffer(r.cells, np.uint8)
    return out


def _ordered(kept: DataFrame, k: int, percent: int, classes, cell_bits: int) -> DataFrame:
    """(digest, n, common, hashes, rests, pieces) of nodes that may have partners: the listed shingles with the number of
    shingles from each on, and the shingles that may be shared, by fragment of the sets."""

    def run(batches):
        for digests, sets in _kept_sets(batches, k):
            n = np.array([len(s) for s in sets], np.int64)
            h, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), n)
            cls = classes.value[(h >> np.uint64(64 - cell_bits)).astype(np.int64)]
            common = np.bincount(owner, cls > 0, len(sets)).astype(np.int64)
            may = common >= least_overlap(n, percent)
            order = np.lexsort((h, cls, owner))
            listed = h[order]
            rest = np.repeat(np.cumsum(n), n) - np.arange(len(h))
            rare = np.cumsum(n) - common  # where each set's shared shingles begin in the order
            stop = np.cumsum(n) - least_overlap(n, percent) + 1
            piece = (h >> np.uint64(61)).astype(np.int64)
            rows: list[list] = [[] for _ in range(6)]
            start = np.cumsum(n) - n
            for i in np.flatnonzero(may):
                a, b = rare[i], max(rare[i], min(stop[i], start[i] + n[i]))
                mine = slice(start[i], start[i] + n[i])
                shared = cls[mine] > 0
                own, part = h[mine][shared].astype(np.int64), piece[mine][shared]
                cuts = np.searchsorted(part, np.arange(SET_FRAGMENTS + 1))
                for col, v in zip(rows, (digests[i], n[i], common[i], listed[a:b].astype(np.int64), rest[a:b].astype(np.int32), [own[x:y] for x, y in zip(cuts[:-1], cuts[1:], strict=True)]), strict=True):
                    col.append(v)
            kinds = (pa.int64(), pa.int32(), pa.int32(), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.list_(pa.list_(pa.int64())))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, kinds, strict=True)], ["digest", "n", "common", "hashes", "rests", "pieces"])

    return kept.mapInArrow(run, "digest long, n int, common int, hashes array<long>, rests array<int>, pieces array<array<long>>")


# -- candidates and links -----------------------------------------------------------------------------------------------
def _join_hot(rows: DataFrame, keyed: DataFrame, key: str, size: str, total: int, how: str = "inner") -> DataFrame:
    """rows joined with ``keyed`` (one row per key, with its number of rows): common keys by broadcast, the others by shuffle."""
    least = max(HOT_LEAST, -(-total // HOT_KEYS))
    hot = F.broadcast(keyed.where(F.col(size) >= least))
    return rows.join(hot, key).unionByName(rows.join(hot.select(key), key, "left_anti").join(keyed.where(F.col(size) < least), key, how))


def _may_link(na: Column, ra: Column, nb: Column, rb: Column, percent: int) -> Column:
    """Whether two sets can reach the threshold if their first common shingle is this one."""
    return (100 * F.least(na, nb) >= percent * F.greatest(na, nb)) & ((100 + percent) * F.least(ra, rb) >= percent * (na + nb))


def _elements(nodes: DataFrame) -> DataFrame:
    e = nodes.select(F.col("digest").alias("node"), "n", (F.col("common") / F.col("n")).alias("share"), F.explode(F.arrays_zip("hashes", "rests")).alias("e"))
    return e.select("node", "n", "share", F.col("e.hashes").alias("h"), F.col("e.rests").alias("rest"))


def _star_pairs(e: DataFrame, total: int, percent: int) -> DataFrame:
    """(a, b): each node b with the centre a it shares most listed shingles with. The centre of a list has the largest
    part of its shingles in common with others."""
    lists = cut_lineage(e.groupBy("h").agg(F.count("*").alias("size"), F.max(F.struct("share", "node", "n", "rest")).alias("c")).where("size > 1"))
    met = _join_hot(e, lists, "h", "size", total).where(F.col("node") != F.col("c.node")).where(_may_link(F.col("n"), F.col("rest"), F.col("c.n"), F.col("c.rest"), percent))
    counts = met.groupBy(F.col("c.node").alias("a"), F.col("node").alias("b")).agg(F.count("*").alias("n"))
    return counts.groupBy("b").agg(F.max(F.struct("n", "a")).alias("best")).select("best.a", "b")


def _cross_pairs(e: DataFrame, labels: DataFrame, total: int, percent: int) -> DataFrame:
    """(a, b): pairs of different components that meet in a list and may reach the threshold. In each list those outside the
    component of its centre meet all; long lists are dealt over blocks."""
    e = e.join(labels.withColumnRenamed("d", "node"), "node", "left").withColumn("label", F.coalesce("label", "node"))
    lists = e.groupBy("h").agg(F.count("*").alias("size"), F.min("label").alias("low"), F.max("label").alias("high"), F.max(F.struct("share", "node", "label")).alias("c")).where("low < high")
    lists = cut_lineage(lists.select("h", "size", F.col("c.label").alias("top"), F.ceil(F.col("size") / BLOCK_ROWS).cast("int").alias("blocks")))
    e = cut_lineage(_join_hot(e, lists, "h", "size", total).select("h", "node", "n", "rest", "label", "top", "blocks"))
    left = e.withColumn("block", F.pmod(F.xxhash64("node"), "blocks").cast("int")).alias("x")
    right = e.where("label <> top").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).alias("y")
    once = (F.col("x.label") == F.col("x.top")) | (F.col("x.node") < F.col("y.node"))
    bound = _may_link(F.col("x.n"), F.col("x.rest"), F.col("y.n"), F.col("y.rest"), percent)
    met = left.join(right, (F.col("x.h") == F.col("y.h")) & (F.col("x.block") == F.col("y.block")) & (F.col("x.label") != F.col("y.label")) & once & bound)
    return met.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct()


PAIRS_A_TASK = 1_000


def _verified(nodes: DataFrame, pairs: DataFrame, percent: int) -> DataFrame:
    """The pairs that reach the threshold: each fragment of the sets counts its part of the overlap, the parts are summed per pair."""
    pairs = cut_lineage(pairs)
    small = pairs.count() <= BROADCAST_PAIRS
    near = F.broadcast if small else lambda df: df
    many = pairs.groupBy("a").agg(F.ceil(F.count("*") / PAIRS_A_TASK).cast("int").alias("salts")).where("salts > 1")
    pieces = nodes.select("digest", "n", F.posexplode("pieces").alias("frag", "piece")).where(F.size("piece") > 0)
    salted = pairs.join(F.broadcast(many), "a", "left").withColumn("salt", F.pmod(F.xxhash64("b"), F.coalesce("salts", F.lit(1))).cast("int"))
    left = pieces.join(near(salted.select("a", F.col("b").alias("digest"), "salt")), "digest").select("a", "salt", "frag", F.col("digest").alias("b"), F.col("n").alias("nb"), F.col("piece").alias("pb"))
    centres = salted.select(F.col("a").alias("digest"), "salt").distinct()
    right = pieces.join(near(centres), "digest").select(F.col("digest").alias("a"), "salt", "frag", F.col("n").alias("na"), F.col("piece").alias("pa"))
    parts = left.join(right, ["a", "salt", "frag"]).select("a", "b", "na", "nb", F.size(F.array_intersect("pa", "pb")).alias("o"))
    sums = parts.groupBy("a", "b", "na", "nb").agg(F.sum("o").alias("o"))
    return cut_lineage(sums.where(100 * F.col("o") >= percent * (F.col("na") + F.col("nb") - F.col("o"))).select("a", "b"))


def connected_components(edges: DataFrame) -> DataFrame:
    """(d, label) with the smallest id of each component, for ids that occur in ``edges`` (a, b)."""
    both = cut_lineage(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = cut_lineage(both.groupBy(F.col("a").alias("d")).agg(F.min("b").alias("m")).select("d", F.least("d", "m").alias("label")))
    while True:
        seen = both.join(labels, both.b == labels.d).groupBy("a").agg(F.min("label").alias("near"))
        step = labels.join(seen, labels.d == seen.a).select("d", F.col("label").alias("old"), F.least("label", "near").alias("label"))
        jump = labels.select(F.col("d").alias("at"), F.col("label").alias("further"))
        step = cut_lineage(step.join(jump, step.label == jump["at"], "left").select("d", "old", F.least("label", "further").alias("label")))
        done = step.where("label < old").isEmpty()
        labels = step.select("d", "label")
        if done:
            return labels


def _links(docs: DataFrame, table: DataFrame, groups: DataFrame, percent: int, k: int) -> DataFrame | None:
    """(d, label): components of digests that have a link; None if none has."""
    spark = docs.sparkSession
    total = table.agg(F.sum("n").alias("s")).first().s or 0
    fragments = max(8, math.ceil(total * 0.35 / COUNT_ROWS))
    hot = F.broadcast(groups.where(F.col("copies") >= max(HOT_LEAST, -(-table.count() // HOT_KEYS))).select(F.col("one.text_key").alias("text_key"), F.col("one.doc_id").alias("hot_id")))
    single = docs.join(hot, "text_key", "left").where("hot_id is null or hot_id <=> doc_id")  # of a text with very many copies one row is enough
    shared = _fragment_rows(single, k, percent, fragments).repartition("frag").sortWithinPartitions("frag").mapInPandas(_shared_counts, "digest long, shared long")
    partner = F.ceil(F.col("n") * percent / 100)
    suspects = shared.groupBy("digest").agg(F.sum("shared").alias("shared")).join(groups, "digest").where(F.col("shared") >= F.greatest(F.lit(1), F.floor(partner * 0.1).cast("long")))
    keep = cut_lineage(suspects.select("digest", "n", F.col("one.doc_id").alias("d"), F.col("one.text_key").alias("text_key")))
    count, kept_total = keep.agg(F.count("*"), F.sum("n")).first()
    if not count:
        return None
    near = F.broadcast if count <= BROADCAST_NODES else lambda df: df
    wanted = near(keep.select("digest", "d", F.col("text_key").alias("key")))
    kept = docs.join(wanted, (docs.text_key == F.col("key")) & docs.doc_id.eqNullSafe(F.col("d"))).select("text", "digest")
    cuts = 1 << max(3, math.ceil(math.log2(max(1, kept_total / FRAGMENT_ROWS))))
    cell_bits = min(MOST_CELL_BITS, max(20, math.ceil(math.log2(kept_total + 1)), cuts.bit_length()))
    classes = spark.sparkContext.broadcast(_classes(kept, k, cuts, cell_bits))
    nodes = cut_lineage(_ordered(kept, k, percent, classes, cell_bits))
    if nodes.count() > nodes.select("digest").distinct().count():  # repeated rows
        nodes = cut_lineage(nodes.dropDuplicates(["digest"]))
    e = _elements(nodes)
    size = nodes.agg(F.sum(F.size("hashes"))).first()[0]
    if not size:
        return None
    links = _verified(nodes, _star_pairs(e, size, percent), percent)
    labels = connected_components(links)
    more = _verified(nodes, _cross_pairs(e, labels, size, percent), percent)
    if not more.isEmpty():
        labels = connected_components(links.union(more))
    classes.unpersist()
    return labels


def _components(docs: DataFrame, percent: int, k: int) -> DataFrame:
    """(doc_id, text_key, n, digest, root, component_id) per row of ``docs`` (doc_id, text_key, text); root tells components apart."""
    table = cut_lineage(shingle_table(docs, k))
    one = F.min_by(F.struct("doc_id", "text_key"), F.struct(F.col("doc_id").isNull(), "doc_id", "text_key")).alias("one")
    groups = cut_lineage(table.where("n > 0").groupBy("digest").agg(F.first("n").alias("n"), F.count("*").alias("copies"), one))
    labels = _links(docs, table, groups, percent, k)
    roots = groups.select("digest", "copies", F.col("one.doc_id").alias("d"), F.col("digest").alias("root"))
    if labels is not None:
        roots = cut_lineage(roots.drop("root").join(labels.withColumnRenamed("d", "digest"), "digest", "left"))
        least = roots.where("label is not null").groupBy("label").agg(F.min("d").alias("least"))
        roots = roots.join(least, "label", "left").select("digest", "copies", F.coalesce("least", "d").alias("d"), F.coalesce("label", "digest").alias("root"))
    roots = cut_lineage(roots.select("digest", "copies", "root", F.col("d").alias("component_id")))
    found = _join_hot(table.where("n > 0"), roots, "digest", "copies", table.count())
    none = table.where("n = 0").withColumn("copies", F.lit(1).cast("long")).withColumn("root", F.lit(None).cast("long")).withColumn("component_id", F.col("doc_id"))
    return found.unionByName(none)


def _input(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("text_key"), F.col(text_col).alias("text"))


def similarity_components(docs: DataFrame, percent: int = 75, k: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id): one row per row of ``docs``."""
    return _components(_input(docs, id_col, text_col), percent, k).select("doc_id", F.col("n").alias("n_shingles"), "component_id")


def drop_near_duplicates(docs: DataFrame, percent: int = 75, k: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each component, the one of the smallest doc_id (then text hash), with all its columns; repeated rows
    of a document stay once."""
    rows = cut_lineage(_components(_input(docs, id_col, text_col), percent, k).select("doc_id", "text_key", "root"))
    by_root = rows.where(F.col("root").isNotNull()).groupBy("root").agg(F.min_by(F.struct("doc_id", "text_key"), F.struct(F.col("doc_id").isNull(), "doc_id", "text_key")).alias("one"), F.count("*").alias("copies"))
    grouped = by_root.where("copies > 1").select("root", "copies", F.col("one.doc_id").alias("keep_id"), F.col("one.text_key").alias("keep_key"))
    met = _join_hot(rows, cut_lineage(grouped), "root", "copies", rows.count())
    out = met.where("not (doc_id <=> keep_id and text_key = keep_key)").select(F.col("doc_id").alias("out_id"), F.col("text_key").alias("out_key")).distinct()
    repeated = cut_lineage(rows.groupBy(F.col("doc_id").alias("out_id"), F.col("text_key").alias("out_key")).agg(F.count("*").alias("n")).where("n > 1").drop("n"))
    own = (F.xxhash64(F.coalesce(docs[text_col], F.lit(""))) == F.col("out_key")) & docs[id_col].cast("long").eqNullSafe(F.col("out_id"))
    left = docs.join(out, own, "left_anti")
    if repeated.isEmpty():
        return left
    return left.join(repeated, own, "left_anti").unionByName(left.join(repeated, own, "left_semi").dropDuplicates([id_col, text_col]))
