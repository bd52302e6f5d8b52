import random

from certsel.llm import lines
from pyspark.sql import functions as F
from test_line_shuffles import shuffled
from test_short_lines import similar


def test_short_pairs_at_the_threshold(spark):
    """Pairs that are barely similar, of 14 to 44 characters: one in a hundred may be missed."""
    rng = random.Random(8)
    rows, pairs = [], []
    while len(pairs) < 400:
        cut = rng.randint(1, 4)
        line = "".join(rng.choice("abcdefghijklmnopqrstuvw") for _ in range(4 + rng.randint(4 * cut + 5, 5 * cut + 20)))
        longest = max(k for k in range(1, len(line) - 5) if similar(line, line[k:]))
        pairs.append((line, line[longest:]))
    for k, (line, copy) in enumerate(pairs):
        rows += [(2 * k, line), (2 * k + 1, copy)]
    got = {r.doc_id: r.text for r in lines.deduplicate_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[2 * k] for k in range(400))
    assert sum(got[2 * k + 1] != "" for k in range(400)) <= 4


def test_rows_of_small_buckets_meet_without_sorting(spark, tmp_path):
    """Buckets of one, two or more rows, whole or parts of large ones: the same meetings as by sorting all, from one shuffle."""
    rng = random.Random(9)
    rows = []
    for bucket in range(3000):
        sketch, fine = rng.getrandbits(63), rng.getrandbits(63)
        for _ in range(rng.choice([1, 1, 1, 1, 1, 2, 2, 2, 3, 5, 9])):
            far = rng.random() < 0.3
            rows.append((rng.getrandbits(62), rng.getrandbits(63) if far else sketch ^ 1 << rng.randrange(60), rng.getrandbits(63) if far else fine, bucket, 3 if bucket % 50 == 0 else 1))
    spark.createDataFrame(rows, "id long, sketch long, fine long, bucket long, parts int").write.parquet(f"{tmp_path}/rows")
    df = spark.read.parquet(f"{tmp_path}/rows")

    def plain(met):
        return {frozenset((r.id, o)) for r in met for o in r.others}, {(r.id, r.bucket) for r in met if r.bucket is not None}

    want, sorting = shuffled(spark, lambda: lines._met(df, ["bucket"], lines.NEAR).collect())
    got, moved = shuffled(spark, lambda: lines._met_of_many(df, ["bucket"], lines.NEAR).collect())
    assert plain(got) == plain(want) and any(len(r.others) == 1 and r.bucket is None for r in got)
    assert moved < 1.5 * sorting


def test_components_grow_by_links(spark):
    found = spark.createDataFrame([(k, 1) for k in (1, 2, 3)] + [(k, 10) for k in (10, 11)] + [(20, 20), (21, 20)], "node long, root long")
    links = spark.createDataFrame([(11, 3), (5, 4), (21, 0), (2, 1)], "a long, b long")
    got = {(r.node, r.root) for r in lines._merged(found, links).collect()}
    assert got == {(1, 1), (2, 1), (3, 1), (10, 1), (11, 1), (20, 0), (21, 0), (0, 0), (4, 4), (5, 4)}
