"""Mixing sources to target weights by systematic sampling.

Targets: the sources, in code-point order with null last, weigh 5, 2, 1 and so
on in turn and share a budget of words; a target stops at a multiple of its
source's size and the excess is shared again by weight.  Filling by weight
under caps has a closed form: with the sources ordered by cap / weight, the
water level is the first (budget - caps so far) / (weights left) that no
remaining cap lies below (later ones only fall), so no driver loop is needed.

Sampling: a document of a source expects target / source size copies.  Within
a source the expectations are summed along the documents ordered by size, one
seeded offset is added, and a document comes once per integer boundary that
its stretch crosses.  Ordering by size spreads the sample over all lengths, so
the words taken stay within about one long document of the target.

Defined results: null text has size 0; null sources form one source; a source
of size 0 has target 0 and no copies; repeated rows are documents of their
own; an empty table gives no rows; other columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rasterruns.llm.common import WORD_PATTERN, materialize, salted_rank

#: Weights in turn, words to take as a share of all words, and the cap in source sizes.
WEIGHTS = (5, 2, 1)
BUDGET = 1.5
CAP = 2.0
#: Steps per doubling of a document's size that order documents within a source, and parts of each step.
SIZE_STEPS = 16
SALTS = 16


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_PATTERN)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, cap: float = CAP) -> DataFrame:
    """``sizes(src, source_size, docs)``, one row per source -> with ``weight`` and ``target``."""
    every = Window.partitionBy(F.lit(0))
    turn = F.row_number().over(every.orderBy(F.col("src").asc_nulls_last())) - 1
    w = sizes.withColumn("weight", F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (turn % len(weights) + 1).cast("int")))
    w = w.withColumn("_cap", F.col("source_size") * F.lit(cap)).withColumn("_total", F.sum("source_size").over(every) * F.lit(budget))
    by_level = every.orderBy(F.col("_cap") / F.col("weight"), F.col("src").asc_nulls_last())
    before = by_level.rowsBetween(Window.unboundedPreceding, -1)
    w = w.withColumn("_spent", F.coalesce(F.sum("_cap").over(before), F.lit(0.0))).withColumn("_left", F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    w = w.withColumn("_level", (F.col("_total") - F.col("_spent")) / F.col("_left"))
    level = F.max(F.when(F.col("_level") * F.col("weight") <= F.col("_cap"), F.col("_level"))).over(every)
    w = w.withColumn("_water", level)
    return w.withColumn("target", F.when(F.col("_water").isNull(), F.col("_cap")).otherwise(F.least("_cap", F.col("_water") * F.col("weight")))).select("src", "source_size", "docs", "weight", "target")


def mix(docs: DataFrame, source: str = "source", text: str = "text", key: str = "doc_id", weights=WEIGHTS, budget: float = BUDGET, cap: float = CAP, seed: int = 17) -> DataFrame:
    """Every row of ``docs`` (without the text) with size, source_size, target, copies and taken.

    One pass reads the text; everything after it moves ids and sizes only.
    """
    rows = materialize(docs.select(docs[key].alias("key"), docs[source].alias("src"), word_count(docs[text]).alias("size")))
    per_source = rows.groupBy("src").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("docs"))
    targets = source_targets(per_source, weights, budget, cap)
    step = F.floor(F.log2(F.col("size") + 1.0) * SIZE_STEPS).cast("long") * SALTS
    part = step + F.pmod(F.xxhash64("key", F.lit(seed)), F.lit(SALTS))
    ranked = salted_rank(rows, ["src"], [F.col("size"), F.xxhash64("key", F.lit(seed)), F.col("key")], part, "rank")
    t = targets.select(F.col("src").alias("_src"), "source_size", "target")
    joined = ranked.join(t, F.col("src").eqNullSafe(F.col("_src"))).drop("_src")
    rate = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(float(cap)))).otherwise(F.lit(0.0))
    offset = F.pmod(F.xxhash64(F.coalesce(F.col("src"), F.lit("")), F.col("src").isNull(), F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)
    joined = joined.withColumn("rate", rate).withColumn("_u", offset)
    end = F.floor((F.col("rank") + 1) * F.col("rate") + F.col("_u"))
    start = F.floor(F.col("rank") * F.col("rate") + F.col("_u"))
    copies = F.least(end - start, F.ceil("rate")).cast("long")
    return joined.withColumn("copies", copies).select(F.col("key").alias(key), F.col("src").alias(source), "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mixed_documents(docs: DataFrame, source: str = "source", text: str = "text", key: str = "doc_id", **law) -> DataFrame:
    """The documents of the mix, with all their columns, each row as often as it is taken.

    A key that stands on several rows is told apart by row content, so copies
    follow the rows and not the key alone.
    """
    names = docs.columns
    rows = docs.toDF(*[f"c{i}" for i in range(len(names))])
    k, s, t = (f"c{names.index(c)}" for c in (key, source, text))
    taken = mix(rows, s, t, k, **law).where("copies > 0").groupBy(F.col(k).alias("mk"), F.col(s).alias("ms"), F.col("size").alias("mz"))
    taken = taken.agg(F.sum("copies").alias("all"), F.count(F.lit(1)).alias("rows"))
    rows = rows.withColumn("z", word_count(F.col(t)))
    joined = rows.join(taken, F.col(k).eqNullSafe(F.col("mk")) & F.col(s).eqNullSafe(F.col("ms")) & (F.col("z") == F.col("mz")))
    alike = F.row_number().over(Window.partitionBy("mk", "ms", "mz").orderBy(F.xxhash64(*rows.columns)))
    joined = joined.withColumn("i", alike)
    times = F.floor(F.col("all") * F.col("i") / F.col("rows")) - F.floor(F.col("all") * (F.col("i") - 1) / F.col("rows"))
    out = joined.withColumn("times", times.cast("int")).where("times > 0").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("times"))))
    return out.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(names)])
