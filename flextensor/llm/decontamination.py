"""Benchmark decontamination by template canonicalisation [native].

Texts become templates: numbers, capitalised words inside a sentence and units after a number are typed placeholders
that keep their value aside; all else is lower-cased words. Windows of ``window`` template words are hash-joined
between documents and benchmark items (items shorter than a window match by one window of their own length, items of
fewer than four words only documents of just these words). Windows match by their template or by their plain words, so
that a copy in other capitals is found as well; windows mostly of placeholders match by plain words alone. Matches of one document and item at the same offset are one occurrence. An item leaks into a
document if an occurrence covers ``min_words`` words of it, or all windows of a shorter item.

Slots are consistent if equal item values stand for equal document values; different ones may fall together. Where a
slot clashes, its windows are dropped unless they match word for word, and the windows left must cover twice
``min_words`` words: a long copy with an edited number leaks, a chance mix of numbers does not.

Defined results: null and empty texts match nothing; repeated rows and ties give one row per (doc_id, item_id); empty
tables give an empty result; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MARK = "\u0001"
# fixed values: units of measure that follow a number
UNITS = "kg|g|mg|km|cm|mm|m|mi|miles|mile|ft|feet|inch|inches|lb|lbs|oz|l|ml|litres|liters|hours|hour|minutes|minute|seconds|second|days|day|weeks|week|months|month|years|year|percent|dollars|dollar|euros|euro|cents|cent|mph|kmh|degrees"
BROADCAST_ROWS = 1_000_000


def template_words(text: Column) -> Column:
    """Words of the template; a placeholder is MARK, its type, its value."""
    t = F.translate(F.coalesce(text, F.lit("")), MARK, " ")
    t = F.regexp_replace(t, r"(?<=[\p{Ll},;:] )(\p{Lu}\p{Ll}+)", MARK + "p$1")
    t = F.regexp_replace(t, r"(?<![\p{L}\p{N}])[0-9]+(?:[.,:/-]?[0-9]+)*", MARK + "n$0")
    t = F.regexp_replace(t, rf"(?<=[0-9] )(?i:({UNITS}))(?![\p{{L}}\p{{N}}])", MARK + "u$1")
    return F.regexp_extract_all(F.lower(t), F.lit(MARK + r"?[\p{L}\p{N}]+(?:[.,:/-][0-9]+)*"), F.lit(0))


def _shift(x: Column, by: int) -> Column:
    return F.slice(x, by + 1, F.greatest(F.size(x) - by, F.lit(0)))


def _grams(rows: DataFrame, name: str, most: int) -> DataFrame:
    """Adds the hashes of 2, 4, 8, .. words from each word on, each from two of half its length, up to ``most``."""
    k = 1
    while 2 * k <= most:
        x = F.col(f"{name}{k}")
        rows = rows.withColumn(f"{name}{2 * k}", F.zip_with(x, _shift(x, k), lambda a, b: F.xxhash64(a, b)))
        k *= 2
    return rows


def _gram(name: str, k: int) -> Column:
    """Hashes of k words from each word on; the last k - 1 are of fewer words."""
    out, at = None, 0
    while at < k:
        part = 1 << ((k - at).bit_length() - 1)
        x = F.col(f"{name}{part}")
        out = x if out is None else F.zip_with(out, _shift(x, at), lambda a, b: F.xxhash64(a, b))
        at += part
    return out


def _windows(df: DataFrame, id_col: str, words: Column, lengths: list[int], whole: int) -> DataFrame:
    """(id, pos, len, h, g, v_0..) for every window of each length: hashes of its template and of its plain words, and of each plain
    word; texts of fewer than ``whole`` words are one window. Arrays are shifted against each other once per text, so the
    work is in proportion to its words."""
    width = max(lengths)
    values = [f"v_{j}" for j in range(width)]
    kind = f"array<struct<pos:int,len:int,h:bigint,g:bigint,{','.join(f'{v}:bigint' for v in values)}>>"
    marked = lambda w: F.startswith(w, F.lit(MARK))
    rows = df.select(F.col(id_col).alias("id"), words.alias("words"))
    rows = rows.select(
        "id",
        F.size("words").alias("n"),
        F.transform("words", lambda w: F.xxhash64(F.when(marked(w), F.substring(w, 1, 2)).otherwise(w))).alias("t1"),
        F.transform("words", lambda w: F.xxhash64(F.when(marked(w), F.substring(w, 3, 1 << 30)).otherwise(w))).alias("p1"),
    )
    rows = _grams(_grams(rows, "t", width), "p", width)
    n, p1 = F.col("n"), F.col("p1")

    def windows(k: int) -> Column:
        every = F.arrays_zip(F.sequence(F.lit(1), n), F.array_repeat(F.lit(k), n), _gram("t", k), _gram("p", k), *(_shift(p1, j) for j in range(width)))
        return F.when(n >= k, F.slice(every, 1, n - k + 1).cast(kind)).otherwise(F.array().cast(kind))

    own = F.xxhash64(p1)
    one = F.array(F.struct(F.lit(1), n, own, own, *(F.get(p1, F.lit(j)) for j in range(width)))).cast(kind)
    each = [*(windows(k) for k in lengths), F.when(n.between(1, whole - 1), one).otherwise(F.array().cast(kind))]
    # the outer form keeps the optimiser from building the windows twice, for a filter on their number
    rows = rows.select("id", F.explode_outer(F.concat(*each)).alias("w")).select("id", "w.*").where(F.col("pos").isNotNull())
    return rows.withColumn("h", F.xxhash64("len", "h")).withColumn("g", F.xxhash64("len", "g"))


def find_leaks(docs: DataFrame, bench: DataFrame, window: int = 8, min_words: int = 12, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """(doc_id, item_id, n_windows, n_slots): every item that leaks into a document."""
    items = bench.select(F.col(item_col).alias("item_id"), template_words(F.col(item_text_col)).alias("words")).where(F.size("words") > 0)
    # a text of few words is held against documents by its own length; one below four words against whole documents
    whole = min(window, 4)
    short = sorted(r.k for r in items.where((F.size("words") < window) & (F.size("words") >= 4)).select(F.size("words").alias("k")).distinct().collect())
    lengths = [window, *short]
    values = [f"v_{j}" for j in range(window)]
    own = F.least(F.size("words"), F.lit(window))
    b = _windows(items, "item_id", F.col("words"), lengths, whole).withColumnRenamed("id", "item_id")
    b = b.join(items.select("item_id", "words", own.alias("own")), "item_id").where(F.col("len") == F.col("own")).dropDuplicates(["item_id", "pos", "h", "g"])
    slots = F.filter(F.sequence(F.lit(0), F.col("len") - 1), lambda j: F.startswith(F.get("words", F.col("pos") - 1 + j), F.lit(MARK)))
    b = b.withColumn("slots", slots)
    by_value = (F.col("len") < whole) | (2 * F.size("slots") > F.col("len"))
    b = b.select("item_id", F.col("pos").alias("ipos"), "len", "slots", F.transform("slots", lambda j: F.get(F.array(*values), j)).alias("i"), by_value.alias("by_value"), "h", F.col("g").alias("ig"))
    # a changed copy can't match windows by value, so all windows of a short item are all that match by template, if any
    totals = b.groupBy("item_id").agg(F.countDistinct("ipos").alias("total"), F.countDistinct(F.when(~F.col("by_value"), F.col("ipos"))).alias("total_open"))
    keys = F.when(F.col("by_value") | (F.size("slots") == 0), F.array("ig")).otherwise(F.array("h", "ig"))
    b = b.select(F.explode(keys).alias("key"), "item_id", "ipos", "len", "slots", "i", "by_value", "ig")
    if b.count() <= BROADCAST_ROWS:
        b = F.broadcast(b)
    d = _windows(docs.select(id_col, text_col), id_col, template_words(F.col(text_col)), lengths, whole).drop("len")
    d = d.select("id", "pos", "g", *values, F.explode(F.when(F.col("h") == F.col("g"), F.array("h")).otherwise(F.array("h", "g"))).alias("key"))
    same = F.col("ig") == F.col("g")
    met = d.join(b, "key").where(same | ~F.col("by_value"))
    met = met.withColumn("d", F.when(same, F.col("i")).otherwise(F.transform("slots", lambda j: F.get(F.array(*values), j))))
    hits = met.select("id", "item_id", (F.col("pos") - F.col("ipos")).alias("offset"), "ipos", "len", "by_value", "i", "d").dropDuplicates(["id", "item_id", "offset", "ipos"])
    key = ["id", "item_id", "offset"]
    found = hits.groupBy(*key).agg(F.count("*").alias("n"), F.max("len").alias("len"), F.count(F.when(~F.col("by_value"), 1)).alias("n_open"), F.collect_set(F.when(F.col("by_value"), F.arrays_zip("i", "d"))).alias("equal"), F.collect_list(F.when(~F.col("by_value") & (F.size("i") > 0), F.arrays_zip("i", "d"))).alias("pairs"))
    found = found.withColumn("slots", F.array_distinct(F.flatten("pairs"))).withColumn("values", F.array_sort(F.transform("slots", lambda s: s["i"])))
    found = found.withColumn("clash", F.filter("values", lambda v, k: v == F.get(F.col("values"), k + 1)))
    lost = F.filter("pairs", lambda w: F.exists(w, lambda s: F.array_contains(F.col("clash"), s["i"])) & F.exists(w, lambda s: s["i"] != s["d"]))
    found = found.withColumn("n_windows", F.when(F.size("clash") > 0, F.col("n") - F.size(lost)).otherwise(F.col("n")))
    covered = F.col("n_windows") + F.col("len") - 1
    every = F.when(F.col("total_open") > 0, F.col("n_open") >= F.col("total_open")).otherwise(F.col("n") >= F.col("total"))
    leak = F.when(F.size("clash") > 0, (F.col("n_windows") > 0) & (covered >= 2 * min_words)).otherwise((covered >= min_words) | every)
    return (
        found.join(totals, "item_id")
        .where(leak)
        .groupBy(F.col("id").alias("doc_id"), "item_id")
        .agg(F.max("n_windows").alias("n_windows"), F.max(F.size(F.array_union("slots", F.flatten("equal")))).cast("long").alias("n_slots"))
    )


def drop_leaks(docs: DataFrame, bench: DataFrame, text_col: str = "text", **how) -> DataFrame:
    """The documents into whose text no item leaks, with all their columns; the same for every row of one text, whatever its id."""
    key = F.xxhash64(docs[text_col])
    texts = docs.select(key.alias("leak_key"), F.col(text_col).alias("text"))
    leaks = find_leaks(texts, bench, id_col="leak_key", text_col="text", **how).select(F.col("doc_id").alias("leak_key")).distinct()
    return docs.join(leaks, key == F.col("leak_key"), "left_anti")
