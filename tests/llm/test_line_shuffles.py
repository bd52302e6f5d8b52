from certsel.llm import lines
from pyspark.sql import functions as F


def shuffled(spark, run):
    """Bytes written to shuffles by run()."""
    def total():
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
        found = spark.sparkContext._jsc.sc().statusStore().executorList(False)
        return sum(found.apply(k).totalShuffleWrite() for k in range(found.size()))

    before = total()
    out = run()
    return out, total() - before


def test_texts_of_lines_without_pairs_are_not_shuffled(spark, tmp_path):
    text = F.concat_ws(" ", *[F.sha2(F.concat(F.col("id").cast("string"), F.lit(f":{k}")), 256) for k in range(8)])
    made = spark.range(4000).withColumn("line", F.when(F.col("id") == 7, F.concat(text, F.lit("!"))).otherwise(text))
    made.withColumn("line", F.when(F.col("id") == 8, F.concat(F.lit("x"), F.regexp_replace("line", "^.", ""))).otherwise(F.col("line"))).write.parquet(f"{tmp_path}/texts")
    texts = spark.read.parquet(f"{tmp_path}/texts")
    near = texts.where("id = 8").select(F.lit(9000).cast("long").alias("id"), F.concat("line", F.lit("?")).alias("line"))
    near.write.mode("append").parquet(f"{tmp_path}/texts")
    texts = spark.read.parquet(f"{tmp_path}/texts")
    pairs = spark.createDataFrame([(8, 7), (9000, 8), (100, 8)], "a long, b long")
    threshold = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        links, moved = shuffled(spark, lambda: lines._verified(pairs, texts, lines.SHINGLE, lines.SIMILARITY).collect())
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)
    assert [(r.a, r.b) for r in links] == [(9000, 8)]
    assert moved < 100_000  # all texts have about 2 MB


def test_repeated_shingles_count_once(spark):
    """Lines that repeat themselves: places alone do not tell similarity, so different shingles are counted."""
    rows = [(1, "abcdef" * 30), (2, "abcdef" * 60), (3, "abcdef" * 30 + "qrstuvwxyz0123"), (4, "the same words twice"), (5, "the same words twicee")]
    sets = {k: {x[i:i + 5] for i in range(len(x) - 4)} for k, x in rows}
    texts = spark.createDataFrame(rows, "id long, line string")
    every = [(a, b) for a in sets for b in sets if a > b]
    got = {(r.a, r.b) for r in lines._verified(spark.createDataFrame(every, "a long, b long"), texts, 5, 0.8).collect()}
    want = {(a, b) for a, b in every if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])}
    assert got == want and (2, 1) in want and len(want) < len(every)
