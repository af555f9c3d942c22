"""Mixing sources to target weights: hash-random order, range buckets, distributed prefix sums, exact cuts.

Every document gets a key from a hash of its id. Ranges of the key split each source into buckets of bounded size,
so the running word count of a source is a sum over earlier buckets plus a running sum inside one bucket: no task
ever holds a source. A source's word budget is cut exactly; a budget above the source's size repeats the source.

Defined results: a null text has size 0; a null source is a source of its own, ranked last; documents without
words take nothing; repeated rows count each; rows that tie on key and id are ordered by size; an empty table
gives an empty mix.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .shared import hash60, small, staged

WEIGHTS, MAX_EPOCHS, SEED = (5, 2, 1), 3, 7
BUCKET_ROWS, MAX_BUCKETS = 4096, 65536
WORDS = r"[^\x20\x09\x0A\x0B\x0C\x0D]+"


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORDS)), F.lit(0)).cast("long")


def source_plan(sizes: DataFrame, weights=WEIGHTS, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """One row per source: source_size, n rows, target (double). Targets share all words by weight; a target stops at
    max_epochs times its source, and what it leaves goes to the others by weight. Sources are ranked by the least
    level at which they stop, so the common level of the rest follows from two running sums."""
    total = sizes.groupBy("__src").agg(F.min("source").alias("source"), F.sum("size").alias("source_size"), F.count("*").alias("__rows"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    turn = (F.row_number().over(by_name) - 1) % len(weights)
    weight = F.element_at(F.array(*[F.lit(int(w)).cast("long") for w in weights]), turn + 1)
    total = total.withColumn("__w", weight).withColumn("__cap", F.col("source_size") * max_epochs)
    order = Window.orderBy(F.col("__cap") / F.col("__w"), F.col("source").asc_nulls_last())
    before, every = order.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    total = total.withColumn("__left", F.sum("source_size").over(every) - F.coalesce(F.sum("__cap").over(before), F.lit(0)))
    total = total.withColumn("__wleft", F.sum("__w").over(every) - F.coalesce(F.sum("__w").over(before), F.lit(0)))
    total = total.withColumn("__full", F.col("__cap") * F.col("__wleft") <= F.col("__left") * F.col("__w"))
    total = total.withColumn("__rest", F.sum("source_size").over(every) - F.sum(F.when(F.col("__full"), F.col("__cap")).otherwise(0)).over(every))
    total = total.withColumn("__wrest", F.sum(F.when(F.col("__full"), 0).otherwise(F.col("__w"))).over(every))
    level = (F.col("__w") * F.col("__rest")).cast("double") / F.col("__wrest").cast("double")
    return total.select("__src", "__rows", "source_size", F.when(F.col("__full"), F.col("__cap").cast("double")).otherwise(level).alias("target"))


def _keyed(docs: DataFrame, seed: int, keep: list[str]) -> DataFrame:
    return docs.select(
        *[F.col(f"`{c}`") for c in keep],
        F.coalesce(F.concat(F.lit("s"), F.col("source").cast("string")), F.lit("n")).alias("__src"),
        word_count(F.col("text")).alias("__size"),
        hash60(F.lit(seed), F.col("doc_id")).alias("__key"),
    )


def _with_taken(rows: DataFrame, narrow: DataFrame, weights, max_epochs: int) -> DataFrame:
    """rows plus source_size, target and taken; narrow: the same rows' (__src, __size, __key), cheap to read."""
    plan = staged(source_plan(narrow.select("__src", F.col("source"), F.col("__size").alias("size")), weights, max_epochs), "mix-plan")
    buckets = F.least(F.lit(MAX_BUCKETS), F.greatest(F.lit(1), F.ceil(F.col("__rows") / BUCKET_ROWS))).cast("long")
    plan = small(plan.withColumn("__n", buckets).withColumn("__budget", F.floor(F.col("target") + 0.5)))
    bucket = F.expr("shiftright(shiftright(__key, 20) * __n, 40)")
    sums = narrow.join(plan.select("__src", "__n"), "__src").groupBy("__src", bucket.alias("__bucket")).agg(F.sum("__size").alias("__sum"))
    earlier = Window.partitionBy("__src").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select("__src", "__bucket", F.coalesce(F.sum("__sum").over(earlier), F.lit(0)).alias("__start"))
    inside = Window.partitionBy("__src", "__bucket").orderBy("__key", "doc_id", "__size").rowsBetween(Window.unboundedPreceding, -1)
    out = rows.join(plan, "__src").withColumn("__bucket", bucket)
    out = out.withColumn("__before", F.coalesce(F.sum("__size").over(inside), F.lit(0))).join(starts, ["__src", "__bucket"])
    epochs = F.when(F.col("source_size") > 0, F.expr("__budget div source_size")).otherwise(F.lit(0))
    rest = F.col("__budget") - epochs * F.col("source_size") - F.col("__start") - F.col("__before")
    return out.withColumn("taken", epochs * F.col("__size") + F.least(F.col("__size"), F.greatest(F.lit(0), rest)))


def mix_plan(docs: DataFrame, weights=WEIGHTS, max_epochs: int = MAX_EPOCHS, seed: int = SEED) -> DataFrame:
    """Per document: doc_id, size, source_size, target, taken (words of it that the mix uses, repeats counted)."""
    rows = staged(_keyed(docs, seed, ["doc_id", "source"]), "mix-sizes")
    taken = _with_taken(rows.drop("source"), rows, weights, max_epochs)
    return taken.select("doc_id", F.col("__size").alias("size"), "source_size", "target", F.col("taken").cast("long").alias("taken"))


def mix_documents(docs: DataFrame, weights=WEIGHTS, max_epochs: int = MAX_EPOCHS, seed: int = SEED) -> DataFrame:
    """The mixed corpus: whole documents, each as often as its taken words need. The one document of a source that
    the budget cuts goes in whole, so a source exceeds its budget by less than one document."""
    keep = docs.columns
    narrow = staged(_keyed(docs, seed, ["doc_id", "source"]), "mix-sizes")
    wide = docs.select(F.struct(*[F.col(f"`{c}`") for c in keep]).alias("__doc"), "doc_id", "source", "text")
    rows = _keyed(wide, seed, ["__doc", "doc_id"])
    taken = _with_taken(rows, narrow, weights, max_epochs).filter("taken > 0")
    copies = F.ceil(F.col("taken") / F.col("__size")).cast("int")
    return taken.select("__doc", F.explode(F.sequence(F.lit(1), copies))).select("__doc.*")
