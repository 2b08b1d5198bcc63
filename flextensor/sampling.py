"""Splits and samples by a portable hash: the same rows in every layout and in any SQL engine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .session import cut_lineage
from .tensor import TensorFrame

MULTIPLIER, INCREMENT, MODULUS = 1_103_515_245, 12_345, 2_147_483_648


def portable_hash(*cols: Column, seed: int = 0) -> Column:
    """A chained congruential hash below 2**31; its high bits are good."""
    h = F.lit(seed).cast("long")
    for c in cols:
        h = F.pmod((F.pmod(h + c.cast("long"), F.lit(MODULUS))) * MULTIPLIER + INCREMENT, F.lit(MODULUS))
    return F.pmod(h * MULTIPLIER + INCREMENT, F.lit(MODULUS))


def portable_hash_sql(*cols: str, seed: int = 0) -> str:
    h = f"{seed}::BIGINT"
    for c in cols:
        h = f"((((({h}) + ({c})) % {MODULUS}) * {MULTIPLIER} + {INCREMENT}) % {MODULUS})"
    return f"((({h}) * {MULTIPLIER} + {INCREMENT}) % {MODULUS})"


def bucket(h: Column, n: int) -> Column:
    """0..n-1 from the high bits."""
    return F.pmod(F.floor(h / 256).cast("long"), F.lit(n)).cast("int")


def kfold(t: TensorFrame, k: int = 5, seed: int = 1) -> DataFrame:
    """Cells with a disjoint, covering ``fold``."""
    return t.df.withColumn("fold", bucket(portable_hash(*(F.col(m) for m in t.modes), seed=seed), k))


def zero_candidates(t: TensorFrame, per_cell: int, seed: int = 3, keep: tuple[Column, ...] = ()) -> DataFrame:
    """Random cells: attempt a of nonzero j draws each index from its hash; no driver loop, no grid. ``keep``: columns of the nonzero."""
    kept = [f"k_{k}" for k in range(len(keep))]
    a = t.df.select(*t.modes, *(c.alias(x) for c, x in zip(keep, kept, strict=True)), F.explode(F.sequence(F.lit(0), F.lit(per_cell - 1))).alias("a"))
    keys = [F.col(m) for m in t.modes] + [F.col("a")]
    # each index mixes the cell's hash with the mode's number, so indices are drawn on their own
    return a.select(*(F.pmod(F.floor(portable_hash(*keys, F.lit(k + 1), seed=seed) / 256).cast("long"), F.lit(d)).alias(m) for k, (m, d) in enumerate(zip(t.modes, t.dims, strict=True))), *kept)


def balanced_sample(t: TensorFrame, ratio: float = 1.0, exclude: DataFrame | None = None, seed: int = 3, attempts: int | None = None) -> TensorFrame:
    """Nonzeros and as many (``ratio``) sampled zeros, disjoint from nonzeros and from ``exclude``; ``origin`` tells them apart. Of
    a given number of ``attempts`` a nonzero the zeros are those that they find, fewer where the grid is nearly full."""
    modes = t.modes
    grid = 1.0
    for d in t.dims:
        grid *= d
    cells = cut_lineage(t.df.select(*modes, "y"))
    t = t.with_df(cells)
    n = cells.count()
    want = round(n * ratio)
    free = max(1e-9, 1 - n / grid)
    if attempts is None and want > grid - n:
        raise ValueError(f"{want} zeros wanted, {grid - n:.0f} cells are empty")
    tries = attempts or _tries(ratio, free, want, grid)
    drawn = zero_candidates(t, tries, seed)

    def empty(drawn: DataFrame) -> DataFrame:
        pool = drawn.distinct().join(t.df.select(*modes), modes, "left_anti")
        return pool if exclude is None else pool.join(exclude.select(*modes), modes, "left_anti")

    # where draws hardly repeat, a bound on the hash with some to spare leaves out what can't be among the smallest before anything is
    # shuffled; if too few are left after all, the whole pool is taken
    share = _share(want, n, tries, free)
    zeros = None
    if attempts is None and 2 * want < grid and share < 0.9:
        low = drawn.where(portable_hash(*(F.col(m) for m in modes), seed=seed + 1) < int(MODULUS * share))
        zeros = _smallest(empty(low), modes, want, seed + 1, whole=False)
    if zeros is None:
        zeros = smallest_hashes(empty(drawn), modes, want, seed + 1)
    cells = cells.withColumn("origin", F.lit("obs")).unionByName(zeros.select(*modes, F.lit(0.0).alias("y"), F.lit("zero").alias("origin")))
    return t.with_df(cells)


def _tries(ratio: float, free: float, want: int, grid: float) -> int:
    """Draws a nonzero: a hash draw repeats cells of a dense grid, so small grids get more of them."""
    return max(2, round(2.5 * ratio / free * (1 + 2 * want / grid)))


def _share(want: int, n: int, tries: int, free: float) -> float:
    return 1.4 * want / max(1.0, n * tries * free)  # more than a few draws meet the same cell: 12 in 100 of six million in a tensor of 4e10


HASH_BINS = 4096


def balanced_folds(t: TensorFrame, k: int, exclude: DataFrame, seed: int = 3) -> DataFrame | None:
    """(modes, y, marks): every nonzero of ``t`` (cells with ``fold``) and the zeros that ``balanced_sample`` takes for each fold's
    training cells, the fold's own nonzeros and ``exclude`` held out. Bit i of ``marks`` stands for a nonzero that trains fold i, bit
    k + i for a zero that does. Draws meet the cells once for all folds. None where folds differ in their draws a cell."""
    modes, grid = t.modes, 1.0
    for d in t.dims:
        grid *= d
    by = {r.fold: r.n for r in t.df.groupBy("fold").agg(F.count("*").alias("n")).collect()}
    want = [sum(by.values()) - by.get(i, 0) for i in range(k)]
    free = [max(1e-9, 1 - n / grid) for n in want]
    tries = {_tries(1.0, f, n, grid) for n, f in zip(want, free, strict=True)}
    if len(tries) > 1 or max(want) > grid - sum(by.values()):
        return None
    h = portable_hash(*(F.col(m) for m in modes), seed=seed + 1)
    source = F.expr("shiftleft(1, fold)")
    taken = F.lit(1 << k).alias("of")
    met = zero_candidates(t, tries.pop(), seed, (source,)).withColumnRenamed("k_0", "of").unionByName(t.df.select(*modes, taken)).unionByName(exclude.select(*modes, taken))
    pool = cut_lineage(met.groupBy(*modes).agg(F.bit_or("of").alias("of")).where(F.col("of") < 1 << k).withColumn("rank_hash", h))
    # a draw is in the pool of each fold that one of its nonzeros trains
    drawn = [F.col("of").bitwiseAND((1 << k) - 1 - (1 << i)) != 0 for i in range(k)]
    b = F.floor(F.col("rank_hash") / (MODULUS // HASH_BINS))
    bins = pool.groupBy(b.alias("b")).agg(*(F.count_if(x).alias(f"n_{i}") for i, x in enumerate(drawn))).orderBy("b").collect()
    marks, key = F.lit(0), F.struct("rank_hash", *modes)
    for i in range(k):
        if not want[i]:
            continue
        seen, found = 0, drawn[i]  # all of them, where draws met too few cells
        for r in bins:
            if seen + r[f"n_{i}"] >= want[i]:
                last = pool.where((b == r.b) & drawn[i]).orderBy("rank_hash", *modes).offset(want[i] - seen - 1).limit(1).select("rank_hash", *modes).first()
                found = found & (key <= F.struct(*(F.lit(x).cast("long").alias(c) for c, x in zip(last.__fields__, last, strict=True))))
                break
            seen += r[f"n_{i}"]
        marks = marks.bitwiseOR(F.when(found, 1 << k + i).otherwise(0))
    zeros = pool.select(*modes, F.lit(0.0).alias("y"), marks.alias("marks")).where("marks > 0")
    return t.df.select(*modes, "y", ((1 << k) - 1 - source).alias("marks")).unionByName(zeros)


def smallest_hashes(pool: DataFrame, modes: list[str], n: int, seed: int) -> DataFrame:
    """The n rows of smallest hash (ties by index). A histogram of the hash finds the one bin in which the n-th lies; only that bin is
    ever ordered."""
    return _smallest(pool, modes, n, seed)


def _smallest(pool: DataFrame, modes: list[str], n: int, seed: int, whole: bool = True) -> DataFrame | None:
    """``smallest_hashes``; of a pool that isn't ``whole`` None if it has fewer rows."""
    pool = cut_lineage(pool.withColumn("rank_hash", portable_hash(*(F.col(m) for m in modes), seed=seed)))
    b = F.floor(F.col("rank_hash") / (MODULUS // HASH_BINS))
    seen = 0
    for r in pool.groupBy(b.alias("b")).agg(F.count("*").alias("n")).orderBy("b").collect():
        if seen + r.n >= n:
            edge = pool.where(b == r.b).orderBy("rank_hash", *modes).limit(n - seen)
            return pool.where(b < r.b).unionByName(edge).drop("rank_hash")
        seen += r.n
    return pool.drop("rank_hash") if whole else None


def enumerated_zeros(t: TensorFrame) -> DataFrame:
    """All empty cells of a tiny tensor."""
    spark = t.df.sparkSession
    out = None
    for m, d in zip(t.modes, t.dims, strict=True):
        r = spark.range(d).select(F.col("id").alias(m))
        out = r if out is None else out.crossJoin(r)
    return out.join(t.df.select(*t.modes), t.modes, "left_anti").withColumn("y", F.lit(0.0))


def hashed_cells(spark: SparkSession, dims: tuple[int, ...], modes: list[str], groups: int, each: int, name: str, seed: int) -> DataFrame:
    """(name, modes): ``each`` random cells of the grid in every group 0..groups-1, drawn index by index from the hash of
    (group, attempt); the grid itself is never made."""
    ids = spark.range(groups * each).select(F.floor(F.col("id") / each).cast("int").alias(name), F.pmod("id", F.lit(each)).alias("a"))
    draws = (F.pmod(F.floor(portable_hash(F.col(name), F.col("a"), F.lit(k + 1), seed=seed) / 256).cast("long"), F.lit(d)).alias(m) for k, (m, d) in enumerate(zip(modes, dims, strict=True)))
    return ids.select(name, *draws)


SMALL_GROUP = 20_000  # rows that one task orders


def _first(df: DataFrame, modes: list[str], name: str, n: int, seed: int) -> DataFrame:
    """Per group the n rows of smallest hash (ties by index). Of large groups a histogram tells the bin in which the n-th lies, and only
    that bin is ordered."""
    h = portable_hash(F.col(name), *(F.col(m) for m in modes), seed=seed)
    if n <= SMALL_GROUP:
        rank = F.row_number().over(Window.partitionBy(name).orderBy(h, *modes))
        return df.withColumn("rank", rank).where(F.col("rank") <= n).drop("rank")
    df = cut_lineage(df.withColumn("rank_bin", F.floor(h / (MODULUS // HASH_BINS)).cast("int")))
    before = F.sum("n").over(Window.partitionBy(name).orderBy("rank_bin")) - F.col("n")
    bins = df.groupBy(name, "rank_bin").agg(F.count("*").alias("n")).withColumn("before", before)
    edges = F.broadcast(bins.where((F.col("before") < n) & (F.col("before") + F.col("n") >= n)).select(name, F.col("rank_bin").alias("edge"), (n - F.col("before")).alias("left")))
    met = df.join(edges, name, "left")
    rank = F.row_number().over(Window.partitionBy(name).orderBy(h, *modes))
    edge = met.where("rank_bin = edge").withColumn("rank", rank).where("rank <= left")
    return met.where("edge IS NULL OR rank_bin < edge").select(*df.columns).unionByName(edge.select(*df.columns)).drop("rank_bin")


def first_of_each(df: DataFrame, modes: list[str], name: str, groups: int, n: int, seed: int) -> DataFrame:
    """(name, columns of ``df``): in each group 0..groups-1 the n rows of smallest hash of (group, modes), or all if there are fewer. A
    group adds a constant to the hash, so one histogram of group 0 tells under which hash each group has its n: no row is ordered in vain."""
    width = MODULUS // HASH_BINS
    b = F.floor(portable_hash(F.lit(0), *(F.col(m) for m in modes), seed=seed) / width)
    counts = [0] * HASH_BINS
    for r in df.groupBy(b.alias("b")).agg(F.count("*").alias("n")).collect():
        counts[r.b] = r.n
    low = []
    for g in range(groups):
        start = -g * pow(MULTIPLIER, len(modes) + 2, MODULUS) % MODULUS  # the hash of group 0 that this group sends to 0
        seen, most, at = 0, width - start % width, start // width
        while seen < n and most < MODULUS:
            at = (at + 1) % HASH_BINS
            seen, most = seen + counts[at], most + width
        low.append(min(most, MODULUS))
    each = df.select("*", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))).alias(name))
    h = portable_hash(F.col(name), *(F.col(m) for m in modes), seed=seed)
    return _first(each.where(h < F.element_at(F.array(*map(F.lit, low)), F.col(name) + 1)), modes, name, n, seed)


def empty_cells(t: TensorFrame, groups: int, n: int, name: str = "rep", seed: int = 5, attempts: int | None = None) -> DataFrame:
    """(name, modes, y = 0): n distinct empty cells in each group; of a given number of ``attempts`` those that they find."""
    free = 1 - t.density()
    grid = 1.0
    for d in t.dims:
        grid *= d
    if attempts is None and n > free * grid:
        raise ValueError(f"{n} zeros wanted, {free * grid:.0f} cells are empty")
    # draws that hit cells or repeat are made up for; on a grid of few empty cells there are more of them
    each = attempts or int(n * (1 + 4 * n / grid) / max(free, 1e-9) * 1.5) + 64
    pool = hashed_cells(t.df.sparkSession, t.dims, t.modes, groups, each, name, seed).distinct()
    return _first(pool.join(t.df.select(*t.modes), t.modes, "left_anti"), t.modes, name, n, seed + 1).withColumn("y", F.lit(0.0))


def fold_zeros(t: TensorFrame, k: int = 5, share: float = 0.001, most: float = 1.0, seed: int = 7, attempts: int | None = None) -> DataFrame:
    """(modes, y = 0, fold): the zeros that each fold tests, ``share`` of all zeros, at most ``most`` times the fold's nonzeros (a
    share of a large grid would swamp them), at least 1."""
    grid = 1.0
    for d in t.dims:
        grid *= d
    n = t.df.count()
    each = max(1, min(int((grid - n) * share + 1e-9), int(n / k * most + 1e-9)))
    return empty_cells(t, k, each, "fold", seed, attempts).select(*t.modes, "y", "fold")


def train_and_tests(t: TensorFrame, share: float = 0.8, reps: int = 50, n_one: int = 200, n_zero: int = 1800, seed: int = 5, attempts: int | None = None) -> tuple[TensorFrame, DataFrame]:
    """``share`` of the nonzeros to train, and (rep, cells, y) test sets of n_one held-out nonzeros and n_zero empty cells each."""
    modes = t.modes
    h = portable_hash(*(F.col(m) for m in modes), seed=seed)
    train = t.df.where(h < int(MODULUS * share))
    rest = t.df.where(h >= int(MODULUS * share)).select(*modes, "y")
    ones = first_of_each(rest, modes, "rep", reps, n_one, seed + 1)
    return t.with_df(train), ones.select("rep", *modes, "y").unionByName(empty_cells(t, reps, n_zero, "rep", seed + 2, attempts).select("rep", *modes, "y"))


def day_pairs(events: DataFrame, days: list[str]) -> DataFrame:
    """Rows with ``pair`` and ``split``: day t trains, day t+1 tests."""
    day = F.to_date("ts").cast("string")
    parts = []
    for i, (a, b) in enumerate(zip(days, days[1:], strict=False)):
        parts += [events.where(day == a).select("*", F.lit(i).alias("pair"), F.lit("train").alias("split")), events.where(day == b).select("*", F.lit(i).alias("pair"), F.lit("test").alias("split"))]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
