"""Samples of a scored universe, for many trials at once: the trial is a column, so 100 trials are one plan.

Sample rows: trial, key, score_u, mult (how often drawn), r_u (reweighting factor times 1e6).
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from certsel.functions.draws import SPACE, hashed, unit
from certsel.sources.staging import staged
from certsel.spec import GRID

POWER_SCALE = 1_000_000
WEIGHT_SCALE = 1_000_000_000
R_SCALE = 1_000_000
#: Score classes of more records are cut into cells by hash prefix, of up to CELL_DIGITS hex digits.
CLASS_ROWS = 4096
CELL_DIGITS = 5
STRIPS = 4096
POISSON_TERMS = 40
#: Sampled keys that are sent to all tasks; beyond it both sides of the join are shuffled.
BROADCAST_KEYS = 1_000_000


def _share_of(budget: int) -> float:
    """Records in which `budget` hashes are found but for a chance of 1e-20."""
    return budget + 10 * math.sqrt(budget) + 50


def uniform_distinct(universe: DataFrame, budget: int, trials: int = 1, seed: int = 0) -> DataFrame:
    """`budget` records drawn without repeats, per trial.

    One hash deals the records over as many trials as have room for their samples beside each other, so a large universe is
    hashed once for all trials; each trial keeps the smallest hashes of its part.  Trials that share a hash share no record.
    """
    n = universe.agg(F.count("*").alias("n"))
    rows = universe.select("key", "score_u").crossJoin(F.broadcast(n))  # one row
    rows = rows.withColumn("parts", F.greatest(F.lit(1), F.floor(F.col("n") / F.lit(_share_of(budget)))).cast("int"))
    rows = rows.withColumn("block", F.explode(F.sequence(F.lit(0), ((F.lit(trials - 1) / F.col("parts"))).cast("int"))))
    rows = rows.withColumn("h", hashed(F.col("key"), F.col("block") + seed, "uniform"))
    at = F.col("h") / F.lit(SPACE) * F.col("parts")
    rows = rows.withColumn("trial", (F.col("block") * F.col("parts") + F.floor(at)).cast("int")).where(F.col("trial") < trials)
    near = rows.where((at - F.floor(at)) * F.col("n") <= F.lit(_share_of(budget)) * F.col("parts"))
    w = Window.partitionBy("trial").orderBy("h", "key")
    return near.withColumn("k", F.row_number().over(w)).where(F.col("k") <= budget).select(
        "trial", "key", "score_u", F.lit(1).cast("long").alias("mult"), F.lit(R_SCALE).cast("long").alias("r_u"))


def histogram(universe: DataFrame) -> DataFrame:
    """(score_u, c), written once: all that weights depend on, a million rows at most."""
    return staged(universe.groupBy("score_u").agg(F.count("*").alias("c")), "classes")


def _power(exponent: float) -> Column:
    return F.round(F.lit(float(POWER_SCALE)) * F.pow(F.col("score_u") / F.lit(float(GRID)), F.lit(float(exponent)))).cast("long")


def _weight(mix: float) -> Column:
    """Integer weight from p_u and the totals n and p_total."""
    share = F.when(F.col("p_total") > 0, F.lit(float(mix)) + F.lit(1.0 - mix) * F.col("n") * F.col("p_u") / F.col("p_total")).otherwise(F.lit(1.0))
    return F.round(F.lit(float(WEIGHT_SCALE)) * share).cast("long")


def weights(universe: DataFrame, exponent: float = 0.5, mix: float = 0.1) -> DataFrame:
    """universe with p_u, w_u and n.  All weights are integers, so sums are exact."""
    u = universe.withColumn("p_u", _power(exponent))
    total = u.groupBy().agg(F.count("*").alias("n"), F.sum("p_u").alias("p_total"))
    return u.crossJoin(F.broadcast(total)).withColumn("w_u", _weight(mix)).drop("p_total")  # one row


def weighted_classes(hist: DataFrame, exponent: float, mix: float, floors: DataFrame | None = None) -> DataFrame:
    """Per score: c records of weight w_u each, and where their span of the running weight total starts and ends.

    With floors (trial, floor), one row a trial, each trial has a universe of its own: the scores from its floor up.
    """
    by = [] if floors is None else ["trial"]
    h = hist if floors is None else hist.join(F.broadcast(floors), F.col("score_u") >= F.col("floor")).select("trial", "score_u", "c")
    h = h.withColumn("p_u", _power(exponent))
    every = Window.partitionBy(*by)
    h = h.withColumn("n", F.sum("c").over(every)).withColumn("p_total", F.sum(F.col("c") * F.col("p_u")).over(every))
    h = h.withColumn("w_u", _weight(mix)).withColumn("span", F.col("c") * F.col("w_u"))
    run = Window.partitionBy(*by).orderBy("score_u").rowsBetween(Window.unboundedPreceding, 0)
    h = h.withColumn("class_end", F.sum("span").over(run)).withColumn("total", F.sum("span").over(every))
    return staged(h.select(*by, "score_u", "c", "n", "w_u", "total", (F.col("class_end") - F.col("span")).alias("class_start"), "class_end"), "spans")


def draws(spark, budget: int, trials: int, seed: int, stream: str, cycle: int | None = None) -> DataFrame:
    d = spark.range(budget * trials).select((F.col("id") / F.lit(budget)).cast("int").alias("trial"), (F.col("id") % budget).alias("j"))
    return d.select("trial", unit(hashed(F.col("j"), F.col("trial") % (cycle or trials) + seed, stream)).alias("u"))


def _strip(x: Column, total: Column) -> Column:
    return F.least(F.lit(STRIPS - 1), F.floor(x / (total / F.lit(float(STRIPS))))).cast("long")


def _in_span(points: DataFrame, spans: DataFrame, on: list[str], at: str, low: str, high: str, size: str) -> DataFrame:
    """points with the span that holds them: both meet on equal strips of the whole, and the bounds are tested within a strip only."""
    cut = spans.withColumn("strip", F.explode(F.sequence(_strip(F.col(low), F.col(size)), _strip(F.col(high) - 1, F.col(size))))).drop(size)
    return points.withColumn("strip", _strip(F.col(at), F.col(size))).join(cut, [*on, "strip"]).where(
        (F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("strip")


def _records(universe: DataFrame, wanted: DataFrame, seed: int) -> DataFrame:
    """(score_u, idx, key): the idx-th record of its score in hash order.  wanted is (score_u, idx, c), c the records of that score.

    Scores of many records are cut into cells by hash prefix; cells are counted first, and records are put in order inside
    the cells that are wanted alone.  Nothing is sorted as a whole, however many records share a score.
    """
    digits = F.when(F.col("c") <= CLASS_ROWS, 0).otherwise(F.least(F.lit(CELL_DIGITS), F.ceil(F.log2(F.col("c") / (CLASS_ROWS / 16)) / 4))).cast("int")
    scores = wanted.select("score_u", "c", digits.alias("digits")).distinct()  # of the draws: as many as these at most
    h = F.substring(F.md5(F.concat_ws(":", F.col("key").cast("string"), F.lit(str(seed)), F.lit("order"))), 1, 13)
    rows = universe.select("key", "score_u").join(F.broadcast(scores), "score_u").withColumn("h", h).withColumn("cell", F.expr("substring(h, 1, digits)"))
    cells = rows.groupBy("score_u", "cell").agg(F.count("*").alias("m"))
    run = Window.partitionBy("score_u").orderBy("cell").rowsBetween(Window.unboundedPreceding, 0)
    cells = cells.withColumn("cell_end", F.sum("m").over(run)).select("score_u", "cell", (F.col("cell_end") - F.col("m")).alias("cell_start"), "cell_end")
    cells = cells.join(F.broadcast(scores.select("score_u", "c")), "score_u")
    hit = _in_span(wanted, cells, ["score_u"], "idx", "cell_start", "cell_end", "c")
    hit = staged(hit.select("score_u", "idx", "cell", (F.col("idx") - F.col("cell_start") + 1).alias("k")), "cells")
    inside = rows.join(F.broadcast(hit.select("score_u", "cell").distinct()), ["score_u", "cell"], "left_semi")  # as many as draws at most
    order = Window.partitionBy("score_u", "cell").orderBy("h", "key")
    return inside.select("score_u", "cell", "key", F.row_number().over(order).alias("k")).join(hit, ["score_u", "cell", "k"]).select("score_u", "idx", "key")


def weighted_cdf(universe: DataFrame, budget: int, trials: int = 1, seed: int = 0, exponent: float = 0.5, mix: float = 0.1,
                 floors: DataFrame | None = None, stream: str = "draw", hist: DataFrame | None = None,
                 cycle: int | None = None) -> DataFrame:
    """`budget` draws with replacement, each record in proportion to its weight, by inverting the running weight total.

    Weights depend on scores alone, so the running total is made over the score histogram: a draw finds its score there, and
    its place among the equally heavy records of that score by division.  Trials share histogram and record order, so a
    universe of its own for each trial (floors) costs no pass over records.  Trials `cycle` apart use the same random numbers.
    """
    by = [] if floors is None else ["trial"]
    classes = weighted_classes(histogram(universe) if hist is None else hist, exponent, mix, floors)
    totals = classes.groupBy(*by).agg(F.max("total").alias("total"))
    d = draws(universe.sparkSession, budget, trials, seed, stream, cycle)
    d = d.join(F.broadcast(totals), by) if by else d.crossJoin(F.broadcast(totals))  # one row, or one a trial
    d = d.withColumn("at", F.floor(F.col("u") * F.col("total")).cast("long"))
    hit = _in_span(d, classes, by, "at", "class_start", "class_end", "total")
    r = F.round(F.lit(float(R_SCALE)) * F.col("total") / (F.col("n") * F.col("w_u"))).cast("long").alias("r_u")
    hit = hit.select("trial", "score_u", "c", r, F.expr("(at - class_start) div w_u").alias("idx"))
    hit = staged(hit.groupBy("trial", "score_u", "c", "idx", "r_u").agg(F.count("*").alias("mult")), "draws")
    found = _records(universe, hit.select("score_u", "idx", "c").distinct(), seed)
    return hit.join(found, ["score_u", "idx"]).select("trial", "key", "score_u", "mult", "r_u")


def uniform_iid(universe: DataFrame, budget: int, trials: int = 1, seed: int = 0, hist: DataFrame | None = None) -> DataFrame:
    """Uniform draws with replacement: equal weights."""
    return weighted_cdf(universe, budget, trials, seed, exponent=0.0, mix=1.0, stream="iid", hist=hist)


def poisson_quantile(u: Column, rate: Column) -> Column:
    """Least k whose Poisson probability sum reaches u; rates up to about 15 are covered by the terms."""
    terms = F.sequence(F.lit(1), F.lit(POISSON_TERMS))
    start = F.struct(F.exp(-rate).alias("p"), F.exp(-rate).alias("c"), F.lit(0).alias("k"))
    walk = F.aggregate(terms, start, lambda a, i: F.struct((a["p"] * rate / i).alias("p"), (a["c"] + a["p"] * rate / i).alias("c"),
                                                          F.when(u > a["c"], i).otherwise(a["k"]).cast("int").alias("k")), lambda a: a["k"])
    return walk


def weighted_poisson(universe: DataFrame, budget: int, seed: int = 0, exponent: float = 0.5, mix: float = 0.1) -> DataFrame:
    """Draws by a map alone: each record has Poisson(rate * weight share) copies from its own hash, with a rate slightly above
    the budget, and the copies of smallest second hash are kept.  Given their number, they are draws in proportion to the weights.

    A record that would expect over 15 copies is cut into several of equal rate first.
    """
    u = weights(universe, exponent, mix)
    total = u.agg(F.sum("w_u").alias("total"))
    u = u.crossJoin(F.broadcast(total))  # one row
    rate = F.lit(budget + 5 * math.sqrt(budget) + 20) * F.col("w_u") / F.col("total")
    u = u.withColumn("rate", rate).withColumn("pieces", F.ceil(F.col("rate") / 15).cast("int"))
    u = u.withColumn("piece", F.explode(F.sequence(F.lit(1), F.greatest(F.lit(1), F.col("pieces")))))
    piece = F.concat_ws("/", F.col("key").cast("string"), F.col("piece").cast("string"))
    c = u.withColumn("copies", poisson_quantile(unit(hashed(piece, seed, "poisson")), F.col("rate") / F.greatest(F.lit(1), F.col("pieces")))).where("copies > 0")
    c = c.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies"))))
    c = c.withColumn("h2", hashed(F.concat_ws("/", F.col("key").cast("string"), F.col("piece").cast("string"), F.col("copy").cast("string")), seed, "keep"))
    kept = c.orderBy("h2", "key").limit(budget)
    r = F.round(F.lit(float(R_SCALE)) * F.col("total") / (F.col("n") * F.col("w_u"))).cast("long")
    return kept.groupBy("key", "score_u", r.alias("r_u")).agg(F.count("*").alias("mult")).select(F.lit(0).alias("trial"), "key", "score_u", "mult", "r_u")


def restrict(universe: DataFrame, floor: Column | int) -> DataFrame:
    """The records scoring at least floor."""
    return universe.where(F.col("score_u") >= floor)


def label(sample: DataFrame, base: DataFrame, oracle) -> DataFrame:
    """The sample with y, written once: whatever runs later, the oracle is asked once for each distinct sampled key.

    Base rows are fetched for those keys (as many as the budget times trials at most; sent to all tasks up to a checked number)
    and the oracle sees these alone.
    """
    drawn = staged(sample, "sample")
    keys = drawn.select("key").distinct()
    keys = F.broadcast(keys) if drawn.count() <= BROADCAST_KEYS else keys
    bought = oracle(base.join(keys, "key", "left_semi")).select("key", F.coalesce("y", F.lit(0)).cast("int").alias("y"))
    return staged(drawn.join(bought, "key"), "labelled")
