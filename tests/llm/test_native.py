"""Sharding, mixing and decontamination against brute force, with edge cases."""

import math
import zlib

import pytest
from pyspark.sql import functions as F

from flextensor.llm import decontamination, mixing, sharding

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, texts, sources=None):
    return spark.createDataFrame([(i, t, "en", sources[i] if sources else "s", None) for i, t in enumerate(texts)], SCHEMA)


def greedy(sizes, capacity):
    n, room = 1, capacity
    for s in sizes:
        if s > capacity:
            return math.inf
        if s > room:
            n, room = n + 1, capacity
        room -= s
    return n


@pytest.mark.parametrize("n_shards", [1, 3, 7, 24])
def test_minimax_capacity_is_the_smallest(spark, n_shards):
    texts = ["x" * (i * 37 % 211) for i in range(300)] + ["hot"] * 150 + [None, "", "y" * 5000]
    docs = frame(spark, texts)
    keyed = docs.select(F.coalesce("text", F.lit("")).alias("t")).select(F.xxhash64("t").alias("h"), (F.octet_length("t") + 8).alias("b"))
    groups = [(r.h, r.b) for r in keyed.groupBy("h").agg(F.sum("b").alias("b")).orderBy("h").collect()]
    sizes = [b for _, b in groups]
    best = next(c for c in range(max(sizes), sum(sizes) + 1) if greedy(sizes, c) <= n_shards)
    cuts, capacity = sharding.find_cuts(keyed.groupBy("h").agg(F.sum("b").alias("bytes")), n_shards)
    assert capacity == best and cuts == sorted(cuts) and len(cuts) < n_shards
    rows = sharding.shard_documents(docs, n_shards).collect()
    assert len(rows) == len(texts)
    by = {}
    for r in rows:
        t = texts[r.doc_id] or ""
        assert r.size == len(t) + 8 and r.text_crc32 == zlib.crc32(t.encode()) and r.law == "bytes" and 0 <= r.shard < n_shards
        by.setdefault(r.shard, []).append(r)
    assert max(sum(r.size for r in v) for v in by.values()) <= best
    for v in by.values():
        assert sorted(r.slot for r in v) == list(range(len(v)))
    homes = {}
    for r in rows:
        homes.setdefault(texts[r.doc_id] or "", set()).add(r.shard)
    assert all(len(s) == 1 for s in homes.values())


def test_shards_of_an_empty_table(spark):
    assert sharding.shard_documents(frame(spark, [])).count() == 0


def test_clashing_columns_do_no_harm(spark):
    docs = frame(spark, ["a b", "c"]).withColumn("size", F.lit(1)).withColumn("shard", F.lit("x")).withColumn("h", F.lit(2)).withColumn("copies", F.lit(1))
    assert sharding.shard_documents(docs).count() == 2
    assert mixing.mix_documents(docs).count() == 2


def water(sizes, cap=3):
    """Targets by repeated resharing."""
    weights = {s: 1 + i % 3 for i, s in enumerate(sorted(sizes, key=lambda s: (s is None, s or "")))}
    total, fixed = sum(sizes.values()), {}
    while True:
        left = total - sum(fixed.values())
        open_ = [s for s in sizes if s not in fixed]
        share = {s: left * weights[s] / sum(weights[x] for x in open_) for s in open_}
        over = [s for s in open_ if share[s] > cap * sizes[s]]
        if not over:
            return fixed | share
        fixed |= {s: cap * sizes[s] for s in over}


def test_mix_targets_and_sizes(spark):
    texts = [" ".join(["w"] * (1 + i * 31 % 40)) for i in range(600)] + [None, "", " \t\n", "a b"]
    sources = [["a", "b", "c", "d", None][(i * i) % 5] if i % 9 else "tiny" for i in range(len(texts))]
    docs = frame(spark, texts, sources)
    rows = mixing.mix_documents(docs).collect()
    assert rows and len(rows) == len(texts)
    sizes, taken, target = {}, {}, {}
    for r in rows:
        s = sources[r.doc_id]
        assert r.size == len([w for w in (texts[r.doc_id] or "").replace("\t", " ").replace("\n", " ").split(" ") if w])
        assert 0 <= r.taken <= 3 * r.size and r.taken == r.size * r.copies
        sizes[s] = sizes.get(s, 0) + r.size
        taken[s] = taken.get(s, 0) + r.taken
        target[s] = r.target
    want = water(sizes)
    for s in sizes:
        assert target[s] == pytest.approx(want[s], rel=1e-9)
        assert abs(taken[s] - target[s]) <= 20.5
    assert sorted(map(tuple, rows)) == sorted(map(tuple, mixing.mix_documents(docs.repartition(7)).collect()))


def test_mix_of_empty_tables(spark):
    assert mixing.mix_documents(frame(spark, [])).count() == 0
    assert [r.taken for r in mixing.mix_documents(frame(spark, [None, ""])).collect()] == [0, 0]


ITEM = "On the last day Maria Lopez carried 17 boxes weighing 40 kg from the harbour to the old mill and counted 17 of them again before night"
BENCH = [(1, ITEM), (2, "short text of five words"), (3, None), (4, ""), (5, "no one else would ever write this plain sentence of fourteen words in a document")]


def leaks(spark, texts):
    b = spark.createDataFrame(BENCH, "item_id long, text string")
    return {(r.doc_id, r.item_id) for r in decontamination.find_leaks(frame(spark, texts), b).collect()}


def test_leaks(spark):
    filler = " ".join(f"filler{chr(97 + i % 26)}{chr(97 + i % 7)}" for i in range(300))
    other = ITEM.replace("Maria Lopez", "Peter Brown").replace("17", "23").replace("40", "55")
    broken = ITEM.replace("17 boxes", "23 boxes")
    texts = [ITEM, f"{filler} {ITEM} {filler}", f"{filler}. {other}. {filler}", broken, filler, None, "", "x", f"a short text of five words {filler}", ITEM.upper(), " ".join(ITEM.split()[:9]), BENCH[4][1], filler + " " + BENCH[4][1][:45]]
    got = leaks(spark, texts)
    assert {(0, 1), (1, 1), (2, 1), (8, 2), (11, 5)} <= got
    assert not {d for d, _ in got} & {3, 4, 5, 6, 7, 10, 12}


def leaks_of(spark, texts, items):
    b = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    return {(r.doc_id, r.item_id) for r in decontamination.find_leaks(frame(spark, texts), b).collect()}


def test_a_clash_costs_only_its_own_windows(spark):
    long = ITEM + " while the keeper of the lamp wrote every single one of these numbers down in a heavy green book that nobody had opened since spring"
    merged = "he bought 3 red apples and then 5 green pears before walking home along the river with his old brown dog"
    texts = [long.replace("17 boxes", "23 boxes"), merged.replace("3", "4").replace("5", "4"), long.replace("17 boxes", "23 boxes").replace("while", "and")[:170]]
    assert leaks_of(spark, texts, [long, merged]) == {(0, 0), (1, 1)}


def test_items_of_numbers_and_names_and_tiny_items(spark):
    numbers = "12 + 30 = 42, 15 + 16 = 31, 70 + 11 = 81, 9 + 8 = 17, 20 + 31 = 51"
    names = "guests: Anna Berg, Carl Dahl, Eva Falk, Gustav Holm, Ida Jansson, Karl Lind, Maja Nord, Olof Persson"
    tiny = "Blue whale"
    texts = [f"some words before {numbers} and after", numbers.replace("12", "13").replace("16", "18").replace("70", "71").replace("9", "6").replace("51", "52"), f"the {names} came", "blue, whale!", "a blue whale came"]
    assert leaks_of(spark, texts, [numbers, names, tiny]) == {(0, 0), (2, 1), (3, 2)}
    # windows that match by value neither clash with changed ones nor are asked of a changed copy
    mixed = "we paid 5 and 6 and 7 then 8 9 10"
    assert leaks_of(spark, [mixed.replace("5", "50")], [mixed]) == {(0, 0)}


def test_leaks_of_empty_tables(spark):
    assert leaks(spark, []) == set()
    b = spark.createDataFrame([], "item_id long, text string")
    assert decontamination.find_leaks(frame(spark, ["a b c"]), b).count() == 0


def test_dropping_keeps_columns(spark):
    b = spark.createDataFrame(BENCH, "item_id long, text string")
    docs = frame(spark, [ITEM, "clean"]).withColumn("item_id", F.lit("z"))
    kept = decontamination.drop_leaks(docs, b)
    assert kept.columns == docs.columns and [r.text for r in kept.collect()] == ["clean"]
