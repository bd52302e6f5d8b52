"""The experiment workloads on the given tables: key, quantised proxy score and oracle.

A workload's base holds key, score_u and what its oracle needs; the oracle is applied to whatever rows it is given, so that a run
labels its sample and only measures label the universe.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from certsel.functions import synth
from certsel.sources.tables import load

# Patterns and word list, portable between Java and RE2.
EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"
INSULTS = ("clown", "disgusting", "idiot", "loser", "moron", "pathetic", "scum", "stupid", "trash", "worthless")
INSULT = "|".join(INSULTS)
#: What the cheap proxy of the audit looks for: a part of the words that the oracle knows.
INSULT_PART = "|".join(INSULTS[:6])
WORD = r"[^\x20\x09-\x0D]+"
VISIBLE_CUT = r"<[^>]*>"
NET_CUT = 105000.0
#: Passages that are sent to all tasks: up to so many characters.
BROADCAST_CHARS = 64_000_000


@dataclass(frozen=True)
class Workload:
    name: str
    key: str
    base: Callable[[SparkSession, str], DataFrame]
    oracle: Callable[[DataFrame], DataFrame]
    budget: int  # of the small-scale queries
    step: int

    def scored(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return self.base(spark, sf_dir)

    def truth(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """(key, score_u, y) of the whole universe: for tests and measures only."""
        return self.oracle(self.base(spark, sf_dir)).select("key", "score_u", "y")


def _bit(c: Column) -> Column:
    """A null oracle counts as no match."""
    return F.coalesce(c, F.lit(False)).cast("int")


def _scored(df: DataFrame, key: Column, score: Column, *payload: Column | str) -> DataFrame:
    return df.select(key.alias("key"), synth.quantised(score).alias("score_u"), *payload)


def _count(col: str, pattern: str) -> Column:
    return F.regexp_count(F.col(col), F.lit(pattern))


def _documents(spark, sf_dir):
    return load(spark, sf_dir, "documents").withColumn("text", F.coalesce("text", F.lit("")))


def _labelled(spark, sf_dir):
    return _documents(spark, sf_dir).join(load(spark, sf_dir, "labels"), "doc_id")


def pii(spark, sf_dir):
    return _scored(_documents(spark, sf_dir), F.col("doc_id"), _count("text", "[0-9]") / F.lit(20), "text", "lang", "source")


def toxic(spark, sf_dir):
    return _scored(_labelled(spark, sf_dir), F.col("doc_id"), _count("text", INSULT) / F.lit(3), "toxic")


def junk(spark, sf_dir):
    d = _labelled(spark, sf_dir)
    return _scored(d, F.col("doc_id"), _count("text", "[^A-Za-zÀ-ÿ]") / F.greatest(F.length("text"), F.lit(1)), "quality")


def junk_ascii(spark, sf_dir):
    d = _labelled(spark, sf_dir)
    return _scored(d, F.col("doc_id"), _count("text", "[^A-Za-z]") / F.greatest(F.length("text"), F.lit(1)), "quality", "lang")


def audit(spark, sf_dir):
    d = _documents(spark, sf_dir).join(load(spark, sf_dir, "labels"), "doc_id", "left_anti")
    return _scored(d, F.col("doc_id"), _count("text", INSULT_PART) / F.lit(2), "text")


def _shingles(df: DataFrame, n: int) -> DataFrame:
    """(key, shingle) pairs, repeats removed, of the words of column text."""
    words = F.regexp_extract_all("text", F.lit(WORD), F.lit(0))
    made = F.transform(F.sequence(F.lit(1), F.size("w") - n + 1), lambda i: F.array_join(F.slice("w", i, n), " "))
    return df.withColumn("w", words).where(F.size("w") >= n).select("key", F.explode(made).alias("shingle")).distinct()


def leak(spark, sf_dir, words: int = 3):
    """Score: distinct shingles shared with any benchmark passage.  The joined passages are an array beside each row."""
    d = _documents(spark, sf_dir).select(F.col("doc_id").alias("key"), "text")
    bench = load(spark, sf_dir, "benchmark").where("text is not null and text <> ''")
    known = _shingles(bench.select(F.col("item_id").alias("key"), "text"), words).select("shingle").distinct()
    shared = _shingles(d, words).join(known, "shingle", "left_semi").groupBy("key").agg(F.count("*").alias("shared"))
    return _scored(d.join(shared, "key", "left"), F.col("key"), F.coalesce("shared", F.lit(0)) / F.lit(20), "text")


def _leak_oracle(sf: DataFrame, bench: DataFrame) -> DataFrame:
    """Nested loop over the given rows: whether the text contains any passage."""
    size = bench.agg(F.sum(F.length("passage"))).first()[0] or 0
    hits = sf.select("key", "text").join(F.broadcast(bench) if size <= BROADCAST_CHARS else bench, F.contains(F.col("text"), F.col("passage")), "left_semi").select("key", F.lit(1).alias("hit"))
    return sf.join(hits, "key", "left").withColumn("y", F.coalesce("hit", F.lit(0))).drop("hit")


def rare(spark, sf_dir):
    return _scored(load(spark, sf_dir, "events"), F.col("event_id"), F.col("value") / F.lit(300), "event_type", "value")


def line_key() -> Column:
    """lineitem has no short unique key: four ids, price in cents and ship date."""
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    return F.concat_ws(":", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", cents, F.date_format("l_shipdate", "yyyy-MM-dd"))


def net(spark, sf_dir):
    return _scored(load(spark, sf_dir, "lineitem"), line_key(), F.col("l_extendedprice") / F.lit(NET_CUT), "l_extendedprice", "l_discount", "l_tax", "l_shipdate")


def bulk(spark, sf_dir):
    orders, lines = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem")
    per = lines.groupBy("l_orderkey").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"))
    d = orders.join(per, orders.o_orderkey == per.l_orderkey, "left")
    return _scored(d, F.col("o_orderkey"), F.coalesce("n", F.lit(0)) / F.lit(20), "qty")


def chat(spark, sf_dir):
    return _scored(load(spark, sf_dir, "conversations"), F.concat_ws(":", "conv_id", "turn"), F.length("text") / F.lit(2000), "role")


EXEMPLARS = 5


def vec(spark, sf_dir, label: int = 3):
    """Cosine to the mean of the first exemplars of a label, mapped to [0, 1]; the exemplars themselves are left out."""
    e = load(spark, sf_dir, "embeddings").select("vec_id", F.transform(F.col("embedding").cast("array<double>"), lambda x: x).alias("v"), "label")
    chosen = e.where(F.col("label") == label).orderBy("vec_id").limit(EXEMPLARS)
    mean = chosen.select("vec_id", F.posexplode("v").alias("i", "x")).groupBy("i").agg(F.array_sort(F.collect_list(F.struct("vec_id", "x"))).alias("xs"))
    mean = mean.select("i", (F.aggregate("xs", F.lit(0.0), lambda a, x: a + x["x"]) / F.size("xs")).alias("m"))
    center = mean.agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda x: x["m"]).alias("c"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    d = e.join(chosen.select("vec_id"), "vec_id", "left_anti").crossJoin(F.broadcast(center))  # one row
    cosine = dot("v", "c") / (F.sqrt(dot("v", "v")) * F.sqrt(dot("c", "c")))
    return _scored(d, F.col("vec_id"), (cosine + 1) / 2, "label")


def page(spark, sf_dir):
    d = load(spark, sf_dir, "pages").withColumn("seen", F.regexp_replace(F.coalesce("html", F.lit("")), VISIBLE_CUT, ""))
    return _scored(d, F.col("page_id"), _count("seen", "[0-9]") / F.lit(40), "html")


def synthetic(alpha: float, beta: float, seed: int = 0, noise: float = 0.0):
    """Labels come from the noiseless score."""

    def base(spark, sf_dir):
        k = load(spark, sf_dir, "lineitem").select(line_key().alias("key"))
        d = k.withColumn("true_u", synth.quantised(synth.beta_score(F.col("key"), alpha, beta, seed)))
        score = synth.noisy(F.col("true_u"), F.col("key"), noise, seed) if noise else F.col("true_u")
        return d.select("key", score.alias("score_u"), "true_u")

    return Workload(f"synth_{alpha}_{beta}_{noise}", "key", base, lambda df: df.withColumn("y", synth.label(F.col("key"), F.col("true_u"), seed)), 2000, 100)


def _make_leak(words: int = 3) -> Workload:
    """The oracle needs the benchmark table that lies beside the documents it is given."""

    def base(spark, sf_dir):
        return leak(spark, sf_dir, words)

    def oracle(df):
        mark = "/documents.parquet"
        (folder,) = {f[:f.index(mark)] for f in df.inputFiles() if mark in f}
        bench = load(df.sparkSession, folder, "benchmark").where("text is not null and text <> ''").select(F.col("text").alias("passage")).distinct()
        return _leak_oracle(df, bench)

    return Workload("leak", "doc_id", base, oracle, 300, 25)


ALL: dict[str, Workload] = {w.name: w for w in (
    Workload("pii", "doc_id", pii, lambda df: df.withColumn("y", _bit(F.col("text").rlike(EMAIL))), 300, 25),
    Workload("tox", "doc_id", toxic, lambda df: df.withColumn("y", _bit(F.col("toxic") == 1)), 150, 15),
    Workload("junk", "doc_id", junk, lambda df: df.withColumn("y", _bit(F.col("quality") == 0)), 150, 15),
    Workload("junk_ascii", "doc_id", junk_ascii, lambda df: df.withColumn("y", _bit(F.col("quality") == 0)), 150, 15),
    Workload("audit", "doc_id", audit, lambda df: df.withColumn("y", _bit(F.col("text").rlike(INSULT))), 200, 20),
    _make_leak(),
    Workload("rare", "event_id", rare, lambda df: df.withColumn("y", _bit((F.col("event_type") == "purchase") & (F.col("value") > 200))), 1000, 100),
    Workload("net", "key", net, lambda df: df.withColumn("y", _bit(F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax")) > NET_CUT)), 2000, 100),
    Workload("bulk", "o_orderkey", bulk, lambda df: df.withColumn("y", _bit(F.col("qty") > 250)), 1500, 100),
    Workload("chat", "key", chat, lambda df: df.withColumn("y", _bit(F.col("role") == "assistant")), 200, 20),
    Workload("vec", "vec_id", vec, lambda df: df.withColumn("y", _bit(F.col("label") == 3)), 200, 20),
    Workload("page", "page_id", page, lambda df: df.withColumn("y", _bit(F.col("html").rlike(EMAIL))), 120, 20),
)}
