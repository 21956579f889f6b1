"""Mixing sources to target weights by entropy balancing.

Each source has a budget of tokens. Document rates are the closest to one, in relative entropy and under an upper bound, that
spend it: rate = min(bound, exp(lambda * size)), one multiplier a source. The dual is convex and splits by source; what it
needs of the documents is how many of each exact size there are. Those cells are rows, and a Newton step of all sources at
once is one aggregate over them, kept inside a shrinking bracket. Sums are exact decimals, so no order of rows changes a step.

Rates are then rounded into copies. Cells in descending order of size take whole numbers of copies by differences of rounded
running sums, which leaves a source off by less than its largest document; that rest is made good in a few cells of each
magnitude of sizes. A cell's copies are dealt to its documents by hash.

Everything here is DataFrame functions. The driver sees one row a step, and one a partition when sources are numbered.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

WEIGHTS = (3.0, 1.0, 2.0)
SHARE = 1.5
BOUND = 2.0
#: Newton steps at most; relative error of a source's tokens at which it stays as it is.
STEPS, CLOSE = 100, 1e-11
#: Groups into which a cell's documents are dealt, so that no cell of many alike texts is ranked in one task.
GROUPS = 4096
#: Cells of a magnitude that make good what rounding leaves of a source.
OFFERED = 8
_EXACT = "decimal(28,9)"


def size_of(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def _numbered(sources: DataFrame) -> DataFrame:
    """Sources with their place i in code-point order, null last: places within sorted partitions, and how many lie before each partition."""
    placed = common.materialise(sources.orderBy("s").withColumn("at", F.monotonically_increasing_id()), "sources")
    part = F.shiftright("at", 33)
    counts = sorted((r["part"], r["n"]) for r in placed.groupBy(part.alias("part")).agg(F.count("*").alias("n")).collect())
    before, total = [], 0
    for k, n in counts:
        before += [F.lit(k), F.lit(total)]
        total += n
    offset = F.element_at(F.create_map(*before), part) if before else F.lit(0)
    return placed.withColumn("i", offset + F.col("at").bitwiseAND((1 << 33) - 1)).drop("at")


def _targets(sources: DataFrame, weights: tuple[float, ...], share: float, bound: float) -> DataFrame:
    """Sources with their target: shares by weight, none above bound times its size.

    Resharing the excess until no source is above its cap raises one level, by which open sources get weight * level; each round
    is one sum over the sources, and the level stays where no further source meets its cap.
    """
    weight = F.get(F.array(*map(F.lit, weights)), F.pmod("i", F.lit(len(weights))).cast("int"))
    s = sources.withColumn("weight", weight).withColumn("cap", F.col("source_size") * bound)
    want = share * float(s.agg(F.sum("source_size")).first()[0] or 0)
    level = 0.0
    while True:
        open_ = F.col("cap") > F.col("weight") * level
        left, full = s.agg(F.sum(F.when(open_, F.col("weight").cast(_EXACT))), F.sum(F.when(~open_, F.col("cap").cast(_EXACT)))).first()
        if not left:
            level = float("inf")
            break
        higher = (want - float(full or 0)) / float(left)
        if higher <= level * (1 + 1e-15):
            break
        level = higher
    target = F.least("cap", F.col("weight") * level) if level < float("inf") else F.col("cap")
    return s.select("s", "source_size", "docs", target.alias("target"))


def _rate(bound: float) -> Column:
    return F.least(F.lit(bound), F.exp(F.least(F.col("lam") * F.col("size") / F.col("mean"), F.lit(50.0))))


def _solve(sources: DataFrame, cells: DataFrame, bound: float) -> DataFrame:
    """Sources with their multiplier `lam` (by size in units of the mean size), from guarded Newton steps of all sources together."""
    mean = F.greatest(F.col("source_size") / F.col("docs"), F.lit(1e-9))
    ratio = F.col("target") / F.greatest("source_size", F.lit(1))
    top = F.log(F.lit(bound))
    full, none = F.col("target") >= F.col("source_size") * bound * (1 - 1e-12), F.col("target") <= 0
    state = sources.withColumn("mean", mean).withColumn("done", full | none)
    # a document has one word at least: at the upper end all rates are at the bound, at the lower one none is above the ratio
    state = state.withColumn("low", F.least(F.col("mean") * F.log(ratio), F.lit(0.0)) - 1).withColumn("high", F.col("mean") * top + 1)
    state = state.withColumn("lam", F.when(full, F.lit(1e9)).when(none, F.lit(-1e9)).otherwise(F.least(F.log(ratio), top)))
    state = common.materialise(state, "multipliers")
    for _ in range(STEPS):
        if state.where("not done").isEmpty():
            break
        grown = F.col("size") / F.col("mean")
        free = F.col("lam") * grown < top
        spent = cells.join(state.where("not done").select("s", "lam", "mean"), "s").groupBy("s").agg(
            F.sum((F.col("tokens") * _rate(bound)).cast(_EXACT)).cast("double").alias("g"),
            F.sum(F.when(free, F.col("tokens") * grown * _rate(bound)).otherwise(0.0).cast(_EXACT)).cast("double").alias("h"),
        )
        met = state.join(spent, "s", "left")
        short = F.coalesce(F.col("g") < F.col("target"), F.lit(False))
        met = met.withColumn("low", F.when(short, F.col("lam")).otherwise(F.col("low"))).withColumn("high", F.when(short, F.col("high")).otherwise(F.col("lam")))
        newton = F.col("lam") - (F.col("g") - F.col("target")) / F.when(F.col("h") > 0, F.col("h"))
        inside = (newton > F.col("low")) & (newton < F.col("high"))
        near = F.coalesce(F.abs(F.col("g") - F.col("target")) <= CLOSE * F.col("target"), F.lit(True)) | (F.col("high") - F.col("low") <= 1e-15 * F.abs("high"))
        moved = F.when(F.col("done") | near, F.col("lam")).when(inside, newton).otherwise((F.col("low") + F.col("high")) / 2)
        new = met.select(*sources.columns, "mean", (F.col("done") | near).alias("done"), "low", "high", moved.alias("lam"))
        old, state = state, common.materialise(new, "multipliers")
        common.discard(old)
    return state.select(*sources.columns, "mean", "lam")


def _copies(sources: DataFrame, cells: DataFrame, bound: float) -> DataFrame:
    """The copies that each cell (s, size, n) takes in all: whole numbers whose tokens meet the source's target."""
    most = F.col("n") * int(bound)
    met = cells.join(sources.select("s", "target", "mean", "lam", "source_size"), "s").withColumn("rate", _rate(bound))
    order = Window.partitionBy("s").orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, 0)
    wanted = F.when(F.col("size") > 0, F.col("n") * F.col("rate")).otherwise(0.0).cast(_EXACT)
    met = met.withColumn("wanted", wanted).withColumn("upto", F.sum("wanted").over(order))
    whole = lambda c: F.floor(c + F.lit(0.5).cast(_EXACT)).cast("long")
    rounded = F.least(most, F.greatest(whole(F.col("upto")) - whole(F.col("upto") - F.col("wanted")), F.lit(0)))
    met = met.withColumn("copies", F.when(F.col("size") > 0, rounded).when(F.col("target") > 0, F.col("n")).otherwise(F.lit(0)).cast("long"))
    met = common.materialise(met.withColumn("most", most), "rounded")
    # what rounding left of each source goes to a few cells of each magnitude, the largest sizes first
    off = met.groupBy("s").agg((F.first("target") - F.sum(F.col("copies") * F.col("size"))).alias("left"))
    room = F.when(F.col("left") > 0, F.col("most") - F.col("copies")).otherwise(F.col("copies"))
    offered = met.where("size > 0").join(off, "s").select("s", "left", "size", "copies", "most", room.alias("room"), F.floor(F.log2("size")).alias("m")).where("room > 0")
    best = Window.partitionBy("s", "m").orderBy(F.desc("room"), "size")
    offered = offered.withColumn("r", F.row_number().over(best)).where(F.col("r") <= OFFERED)
    offered = offered.groupBy("s", "left").agg(F.sort_array(F.collect_list(F.struct("size", "copies", "most")), asc=False).alias("cells"))  # 63 * OFFERED at most

    def deal(a: Column, c: Column) -> Column:
        change = F.greatest(-c.copies, F.least(c.most - c.copies, F.round(a.left / c.size).cast("long")))
        return F.struct((a.left - change * c.size).alias("left"), F.concat(a.out, F.array(F.struct(c.size.alias("size"), change.alias("change")))).alias("out"))

    start = F.struct(F.col("left"), F.array().cast("array<struct<size:bigint,change:bigint>>").alias("out"))
    fixed = offered.select("s", F.explode(F.aggregate("cells", start, deal).out).alias("x")).select("s", "x.size", "x.change").where("change <> 0")
    return met.join(fixed, ["s", "size"], "left").select("s", "size", "n", "source_size", "target", "rate", (F.col("copies") + F.coalesce("change", F.lit(0))).alias("copies"))


def mix(docs: DataFrame, source_col: str = "source", key: list[str] | None = None, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, bound: float = BOUND) -> DataFrame:
    """All columns of `docs` with __size, __source_size, __target, __rate and __copies (0 to bound, a whole number) of each row.

    Size is the number of words of `text` (null: 0), counted over whole texts of any length. `weights` repeat over the sources in code-point
    order, null last, as a source of its own. Together the sources aim at `share` of all words; none aims above `bound` times its own. A
    source's copies meet its target to about the size of its smallest texts. Copies depend on the rows alone: a rerun
    agrees. `key` (default doc_id) breaks ties between equal sizes by hash; rows alike in key and size share their
    rank's order arbitrarily but not their number. Texts without words get one copy where their source's target isn't 0. Extra columns pass
    through (two leading underscores are reserved); an empty table stays empty.
    """
    return mix_sized(docs.withColumn("__size", size_of(F.col("text"))), source_col, key, weights, share, bound)


def mix_sized(docs: DataFrame, source_col: str = "source", key: list[str] | None = None, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, bound: float = BOUND) -> DataFrame:
    """mix() of rows that have their __size; texts aren't read."""
    key = [F.col(k).cast("string") for k in key or ["doc_id"]]
    sized = docs.withColumn("__group", F.pmod(F.xxhash64(*key, F.lit(1)), F.lit(GROUPS)).cast("int"))
    sized = sized.withColumn("__s", F.struct(F.col(source_col).isNull().alias("none"), F.coalesce(F.col(source_col).cast("string"), F.lit("")).alias("name")))
    sized = common.materialise(sized, "sized")  # words are counted once
    groups = common.materialise(sized.groupBy(F.col("__s").alias("s"), F.col("__size").alias("size"), F.col("__group").alias("group")).agg(F.count("*").alias("n")), "groups")
    cells = common.materialise(groups.groupBy("s", "size").agg(F.sum("n").alias("n")).withColumn("tokens", F.col("n") * F.col("size")), "cells")
    sources = _numbered(cells.groupBy("s").agg(F.sum("tokens").alias("source_size"), F.sum("n").alias("docs")))
    solved = _solve(common.materialise(_targets(sources, weights, share, bound), "targets"), cells, bound)
    copies = _copies(solved, cells, bound).withColumnRenamed("n", "all")
    # all documents of a cell get the whole part; those of least hash one more, so all groups but one are in or out as a whole
    order = Window.partitionBy("s", "size").orderBy("group").rowsBetween(Window.unboundedPreceding, 0)
    quota = groups.withColumn("upto", F.sum("n").over(order)).join(copies, ["s", "size"])
    extra = F.least(F.col("n"), F.greatest(F.lit(0), F.col("copies") % F.col("all") - F.col("upto") + F.col("n")))
    quota = quota.select(
        F.col("s").alias("__s"),
        F.col("size").alias("__size"),
        F.col("group").alias("__group"),
        F.col("source_size").alias("__source_size"),
        F.col("target").alias("__target"),
        F.col("rate").alias("__rate"),
        F.expr("copies div all").alias("__each"),
        extra.alias("__extra"),
    )
    met = sized.join(quota, ["__s", "__size", "__group"])
    ranked = Window.partitionBy("__s", "__size", "__group").orderBy(F.xxhash64(*key, F.lit(2)), *key)
    met = met.withColumn("__copies", (F.col("__each") + F.when(F.row_number().over(ranked) <= F.col("__extra"), 1).otherwise(0)).cast("long"))
    return met.select(*[c for c in docs.columns if c != "__size"], "__size", "__source_size", "__target", "__rate", "__copies")


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", size_of(F.col("text")).alias("__size"))
    out = mix_sized(docs)
    return out.select("doc_id", F.col("__size").alias("size"), F.col("__source_size").alias("source_size"), F.col("__target").alias("target"), (F.col("__size") * F.col("__copies")).alias("taken"))
