"""Mixing sources to target weights by Pareto order sampling [native].

Each source gets a share of all words by its weight, no more than ``cap`` times its own words; what is cut off there is
reshared by weight among the rest. A source whose target is f times its size takes floor(f) whole copies of every
document for certain. The remainder is a sample with inclusion probability p = f - floor(f): documents are ranked by
their random odds u/(1-u) over the inclusion odds p/(1-p), u being a hash of the document's id, and taken in this
order until the words taken are as near the target as whole documents allow.

The rank is cut through a histogram of (source, bin of u): only the documents of the one bin in which a source's
sample ends are ever ordered against each other.

Defined results: null texts have size 0; null is a source of its own and comes last; a null id is hashed as the empty
string; repeated rows all count and all are taken equally often; an empty table gives an empty result; further columns of the input are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut_lineage

WORD = r"[^\x20\x09-\x0D]+"
BINS = 4096
DIGITS = 13  # hex digits of the id's md5 that make u


def uniform_of(col: Column) -> Column:
    """A number in (0, 1) that depends on the id alone, the same in every engine that has md5."""
    x = F.conv(F.substring(F.md5(F.coalesce(col.cast("string"), F.lit("")).cast("binary")), 1, DIGITS), 16, 10).cast("double")
    return (x + 0.5) / float(16**DIGITS)


def source_targets(sizes: DataFrame, cap: int = 3, period: int = 3) -> DataFrame:
    """(source, source_size, target) from (source, source_size): weights 1..period by code point, null last."""
    dec = lambda c: c.cast("decimal(38,0)")
    s = sizes.withColumn("w", ((F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % period + 1).cast("long"))
    # the sources that stop at their cap are a prefix of the order by cap over weight
    order = [(F.col("source_size") / F.col("w")).asc(), F.col("source").asc_nulls_last()]
    all_, upto, rest = Window.partitionBy(), Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1), Window.orderBy(*order).rowsBetween(0, Window.unboundedFollowing)
    s = s.select(
        "*",
        F.sum("source_size").over(all_).alias("total"),
        (cap * F.coalesce(F.sum("source_size").over(upto), F.lit(0))).alias("before"),
        F.sum("w").over(rest).alias("w_rest"),
        F.row_number().over(Window.orderBy(*order)).alias("rn"),
    )
    s = s.withColumn("capped", dec(F.col("total") - F.col("before")) * dec(F.col("w")) >= dec(cap * F.col("source_size")) * dec(F.col("w_rest")))
    open_ = F.min(F.when(~F.col("capped"), F.struct("rn", (F.col("total") - F.col("before")).alias("left"), "w_rest"))).over(all_)
    s = s.withColumn("open", open_)
    share = (F.col("open.left") * F.col("w")).cast("double") / F.col("open.w_rest").cast("double")
    return s.select("source", "source_size", F.when(F.col("capped"), (cap * F.col("source_size")).cast("double")).otherwise(share).alias("target"))


def _mix(docs: DataFrame, cap: int, id_col: str, text_col: str, source_col: str) -> DataFrame:
    """(doc_id, source, text_key, size, source_size, target, taken, copies) per row; equal rows get equal numbers."""
    rows = cut_lineage(
        docs.select(
            F.col(id_col).alias("doc_id"),
            F.col(source_col).alias("source"),
            F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("text_key"),
            F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
            uniform_of(F.col(id_col)).alias("u"),
        )
    ).withColumn("bin", F.floor(F.col("u") * BINS).cast("int"))
    bins = rows.groupBy("source", "bin").agg(F.sum("size").alias("s"))
    targets = source_targets(bins.groupBy("source").agg(F.sum("s").alias("source_size")), cap)
    f = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    targets = targets.withColumn("whole", F.floor(f).cast("long")).withColumn("need", F.col("target") - F.col("whole") * F.col("source_size"))
    targets = targets.withColumn("p", F.when(F.col("source_size") > 0, F.col("need") / F.col("source_size")).otherwise(0.0))
    upto = Window.partitionBy("source").orderBy("bin")
    t = targets.alias("t")
    cum = bins.withColumn("cum", F.sum("s").over(upto)).alias("b").join(t, F.col("b.source").eqNullSafe(F.col("t.source")))
    cut = (
        cum.where((F.col("need") > 0) & (F.col("cum") >= F.col("need")))
        .groupBy(F.col("b.source").alias("source"))
        .agg(F.min(F.struct(F.col("bin"), (F.col("need") - (F.col("cum") - F.col("s"))).alias("left"))).alias("cut"))
        .alias("c")
    )
    plan = t.join(cut, F.col("t.source").eqNullSafe(F.col("c.source")), "left").select("t.*", F.col("cut.bin").alias("cut_bin"), F.col("cut.left").alias("left"))
    plan = cut_lineage(plan.withColumnRenamed("source", "plan_source"))
    joined = rows.join(plan, rows.source.eqNullSafe(plan.plan_source)).drop("plan_source")
    clear = joined.where(F.col("cut_bin").isNull() | (F.col("bin") != F.col("cut_bin"))).withColumn("extra", (F.col("cut_bin").isNotNull() & (F.col("bin") < F.col("cut_bin"))).cast("long"))
    odds = (F.col("u") * (1 - F.col("p"))) / ((1 - F.col("u")) * F.col("p"))
    run = F.sum("size").over(Window.partitionBy("source").orderBy("rank", "doc_id", "text_key").rangeBetween(Window.unboundedPreceding, Window.currentRow))
    edge = joined.where(F.col("bin") == F.col("cut_bin")).withColumn("rank", odds).withColumn("extra", (run - F.col("size") / 2 <= F.col("left")).cast("long")).drop("rank")
    copies = F.col("whole") + F.col("extra")
    return clear.unionByName(edge).select("doc_id", "source", "text_key", "size", "source_size", "target", (F.col("size") * copies).alias("taken"), copies.alias("copies"))


def mix_documents(docs: DataFrame, cap: int = 3, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, size, source_size, target, taken, copies) per row."""
    return _mix(docs, cap, id_col, text_col, source_col).drop("source", "text_key")


def take_documents(docs: DataFrame, cap: int = 3, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mix itself: each row of ``docs``, with all its columns, as often as it is taken."""
    plan = _mix(docs, cap, id_col, text_col, source_col).where("copies > 0").select(F.col("doc_id").alias("mix_id"), F.col("source").alias("mix_source"), "text_key", F.col("copies").alias("mix_copies")).distinct()
    own = docs[id_col].eqNullSafe(F.col("mix_id")) & docs[source_col].eqNullSafe(F.col("mix_source")) & (F.xxhash64(F.coalesce(docs[text_col], F.lit(""))) == F.col("text_key"))
    names = [docs[c] for c in docs.columns]
    return docs.join(plan, own).select(*names, F.explode(F.sequence(F.lit(1), F.col("mix_copies").cast("int"))).alias("mix_copy")).drop("mix_copy")
