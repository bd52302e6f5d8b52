"""Mixing sources to target weights by capped water-filling, with seeded whole and fractional repetitions.

Targets: sources share a budget by weight; a source stops at max_epochs times its size and what it leaves is shared
again by weight, until none is above.  The end state has one water level: with sources in order of cap / weight, the
first ones are at their caps and the others at level * weight, which running sums over the sources give in closed form.

Sampling: a source whose target is r times its size repeats every document floor(r) times.  The words left over go to
documents in the order of a seeded hash until they are used up, the last document taken in part; so what a source
takes differs from its target by less than one word.  The order is by cell (three hex digits of the hash) and within
it, so sums are made per cell and no window holds more than one cell of one source.

DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, text_or_empty

WEIGHTS = (3, 1, 2)
BUDGET = 1.5
MAX_EPOCHS = 2
CELL_DIGITS = 3


def sized(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = 0) -> DataFrame:
    """(doc_id, source, size, h): size in words, h the seeded hash that orders documents."""
    text = text_or_empty(F.col(text_col).cast("string"))
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"),
                    F.regexp_count(text, F.lit(WORD)).cast("long").alias("size"))
    return d.withColumn("h", F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col("doc_id").cast("string"), F.lit("-")))))


def _rank_weight(weights, rank: Column) -> Column:
    return F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((rank - 1) % len(weights) + 1).cast("int"))


def targets(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """(source, source_size, weight, target) from rows (source, size).

    Sources are ranked by code point, null last, and weigh `weights`, repeating.  The budget is `budget` times all words.
    One window over all sources: they are one row each.  A source without words has target 0.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    ranked = per.withColumn("weight", _rank_weight(weights, F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))))
    ranked = ranked.withColumn("cap", (F.col("source_size") * max_epochs).cast("double"))
    by_ratio = Window.orderBy((F.col("cap") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    after = by_ratio.rowsBetween(0, Window.unboundedFollowing)
    every = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    filled = ranked.select("source", "source_size", "weight", "cap", (F.sum("source_size").over(every) * F.lit(budget)).alias("total"),
                           F.coalesce(F.sum("cap").over(before), F.lit(0.0)).alias("capped"), F.sum("weight").over(after).alias("open_weight"))
    filled = filled.withColumn("level", (F.col("total") - F.col("capped")) / F.col("open_weight"))
    # The level that holds is the one of the first source it leaves below its cap; later sources' levels are not higher.
    free = filled.withColumn("found", F.max(F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.col("level"))).over(every))
    return free.select("source", "source_size", "weight", F.when(F.col("found").isNull(), F.col("cap")).otherwise(
        F.least(F.col("cap"), F.col("found") * F.col("weight"))).alias("target"))


def allocate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights=WEIGHTS,
             budget: float = BUDGET, max_epochs: int = MAX_EPOCHS, seed: int = 0) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target (its source's), taken (words, repeats counted).

    Null texts have size 0; null sources are one source, ranked last; null ids are one more id.  Rows that repeat an id
    are separate documents.  Empty documents take 0.  The order of documents depends on seed and id alone, so reruns
    agree; equal hashes are ordered by size.  No rows in, no rows out.
    """
    d = sized(docs, id_col, text_col, source_col, seed).withColumn("cell", F.substring("h", 1, CELL_DIGITS))
    t = targets(d, weights, budget, max_epochs)
    by_source = Window.partitionBy("source").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    cells = d.groupBy("source", "cell").agg(F.sum("size").alias("words"))
    cells = cells.select("source", "cell", F.coalesce(F.sum("words").over(by_source), F.lit(0)).alias("before_cell"))
    t = t.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long"))
    t = t.withColumn("extra", F.floor(F.col("target") + 0.5).cast("long") - F.col("whole") * F.col("source_size"))
    cells = cells.join(t.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s"))).select(
        F.col("source").alias("s"), F.col("cell").alias("c"), "source_size", "target", "whole", (F.col("extra") - F.col("before_cell")).alias("left"))
    in_cell = Window.partitionBy("source", "cell").orderBy("h", "size", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    run = d.withColumn("before", F.coalesce(F.sum("size").over(in_cell), F.lit(0)))
    j = run.join(cells, F.col("source").eqNullSafe(F.col("s")) & (F.col("cell") == F.col("c")))
    part = F.least(F.col("size"), F.greatest(F.lit(0), F.col("left") - F.col("before")))
    return j.select("doc_id", "source", "size", "source_size", "target", (F.col("whole") * F.col("size") + part).cast("long").alias("taken"))


def mixed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **settings) -> DataFrame:
    """The mix as rows of docs: each document as often as taken / size, rounded to whole copies (one document of a
    source can be taken in part).  Documents without words are kept once.  Columns as in docs."""
    plan = allocate(docs, id_col, text_col, source_col, **settings)
    copies = plan.groupBy("doc_id").agg(F.max(F.when(F.col("size") == 0, 1).otherwise(F.floor(F.col("taken") / F.col("size") + 0.5))).cast("int").alias("copies__"))
    copies = copies.where("copies__ > 0").withColumnRenamed("doc_id", "id__")
    j = docs.join(copies, F.col(id_col).cast("long").eqNullSafe(F.col("id__")))
    return j.withColumn("copy__", F.explode(F.sequence(F.lit(1), F.col("copies__")))).select(*[j[c] for c in docs.columns])


SQL = r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
                  md5('0:' || coalesce(doc_id::VARCHAR, '-')) AS h FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
r AS (SELECT source, source_size, (source_size * 2)::DOUBLE AS cap,
             CAST([3, 1, 2][((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT] AS DOUBLE) AS weight FROM s),
f AS (SELECT source, source_size, weight, cap, sum(source_size) OVER ()::DOUBLE * 1.5::DOUBLE AS total,
             coalesce(sum(cap) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS capped,
             sum(weight) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS open_weight FROM r),
g AS (SELECT *, (total - capped) / open_weight AS level FROM f),
k AS (SELECT max(level) AS found FROM g WHERE level * weight <= cap),
t AS (SELECT source, source_size, CASE WHEN found IS NULL THEN cap ELSE least(cap, found * weight) END AS target FROM g, k),
w AS (SELECT source, source_size, target, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS whole FROM t),
o AS (SELECT doc_id, source, size, coalesce(sum(size) OVER (PARTITION BY source ORDER BY h, size, doc_id
             ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before FROM d)
SELECT o.doc_id, o.source, o.size, w.source_size, w.target,
       (w.whole * o.size + least(o.size, greatest(0, floor(w.target + 0.5)::BIGINT - w.whole * w.source_size - o.before)))::BIGINT AS taken
FROM o JOIN w ON o.source IS NOT DISTINCT FROM w.source
"""
