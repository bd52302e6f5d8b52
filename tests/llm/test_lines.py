import random
import re

from certsel.llm import lines
from pyspark.sql import functions as F


def shingles(line, k=lines.SHINGLE):
    return {line[i:i + k] for i in range(len(line) - k + 1)} or {line}


def plain(docs, similarity=lines.SIMILARITY):
    """Text of each document by comparing all pairs of lines."""
    places = [((d, p), x.strip(" ").lower()) for d, t in docs for p, x in enumerate((t or "").split("\n")) if x.strip(" ")]
    texts = sorted({x for _, x in places})
    sets = {x: shingles(x) for x in texts}
    root = {x: x for x in texts}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(texts):
        for b in texts[:i]:
            n = len(sets[a] & sets[b])
            if n >= similarity * (len(sets[a]) + len(sets[b]) - n):
                root[find(a)] = find(b)
    owner = {}
    for place, x in sorted(places):
        owner.setdefault(find(x), place)
    keep = {p for p in owner.values()}
    gone = {p for p, _ in places} - keep
    return {d: "\n".join(x for p, x in enumerate(t.split("\n")) if (d, p) not in gone) if t is not None else None for d, t in docs}


def check(spark, docs):
    df = spark.createDataFrame(docs, "doc_id long, text string").withColumn("n_lines", F.lit("x")).repartition(3)
    got = lines.deduplicate_lines(df)
    assert {r.doc_id: r.text for r in got.collect()} == plain(docs)


def test_documents_match_all_pairs(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    check(spark, docs)


def test_near_lines(spark):
    rng = random.Random(3)
    words = ["".join(rng.choice("abcdefghilmnoprstu") for _ in range(rng.randint(2, 9))) for _ in range(400)]
    made = []
    for _ in range(40):
        line = " ".join(rng.choice(words) for _ in range(25))
        made.append(line)
        for _ in range(rng.randint(0, 6)):
            at = rng.randrange(len(line))
            made.append(line[:at] + rng.choice("xyzé") + line[at + 1:])
    rng.shuffle(made)
    check(spark, [(k, "\n".join(made[k * 7:k * 7 + 7])) for k in range(len(made) // 7 + 1)])


def test_edges(spark):
    docs = [(1, None), (2, ""), (3, "\n \n"), (4, "One line here\n\nONE LINE HERE \nx"), (5, "x\ny"), (6, "z " * 20000 + "\nx")]
    check(spark, docs)
    rows = spark.createDataFrame([(None, "a long line of words"), (7, "a long line of words"), (7, "a long line of words"), (7, "another text of words")], "doc_id long, text string")
    got = sorted(((r.doc_id, r.text, r.n_lines, r.n_dropped) for r in lines.deduplicate_lines(rows).collect()), key=str)
    assert got == sorted([(None, "a long line of words", 1, 0), (7, "", 1, 1), (7, "", 1, 1), (7, "another text of words", 1, 0)], key=str)
    assert lines.deduplicate_lines(rows.limit(0)).count() == 0


def test_only_native_operators(spark, sf):
    plan = lines.deduplicate_lines(spark.read.parquet(f"{sf}/documents.parquet").limit(20))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)
