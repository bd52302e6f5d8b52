import random

import xxhash

from certsel.llm.components import components
from certsel.llm.simhash import colliding, deduplicate, fingerprint, links, near_groups
from pyspark.sql import functions as F


def plain_fingerprint(text):
    words = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    for c in "\t\n\x0b\x0c\r":
        words = words.replace(c, " ")
    words = [w for w in words.split(" ") if w]
    if not words:
        return 0
    shingles = [" ".join(words[i:i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    hashes = [xxhash.xxh64(s.encode(), seed=42).intdigest() for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def classes(pairs, nodes):
    root = {n: n for n in nodes}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def test_fingerprints(spark):
    texts = ["", None, "One", "one two", "One TWO three", "É a b c a b c a b c", "x\ty\nz\x0bw\x1cv\x85u", " lead  trail "]
    assert [fingerprint(t) for t in texts] == [plain_fingerprint(t) for t in texts]
    rows = spark.createDataFrame([(t,) for t in texts if t], "t string").select(F.xxhash64("t").alias("h"), "t").collect()
    assert all(r.h % 2**64 == xxhash.xxh64(r.t.encode(), seed=42).intdigest() for r in rows)


def test_groups_match_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
    fp = {k: plain_fingerprint(t) for k, t in texts.items()}
    want = classes([(a, b) for a in fp for b in fp if a < b and (fp[a] ^ fp[b]).bit_count() <= 3], fp)
    got = near_groups(docs).collect()
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in got} == {k: (f"{fp[k]:016x}", want[k]) for k in fp} and len(got) == len(fp)


def test_every_distance_is_linked(spark):
    rng = random.Random(4)
    fps = []
    for _ in range(60):
        x = rng.getrandbits(64)
        fps.append(x)
        for d in (1, 2, 3, 4, 5):
            y = x
            for b in rng.sample(range(64), d):
                y ^= 1 << b
            fps.append(y)
    fps = sorted(set(fps) | {0, 1, 2**63, 2**64 - 1})
    signed = [x - 2**64 if x >> 63 else x for x in fps]
    want = classes([(a, b) for a in fps for b in fps if a < b and (a ^ b).bit_count() <= 3], fps)
    df = spark.createDataFrame([(x,) for x in signed], "fp long")
    near = colliding(df)
    assert {r.fp % 2**64 for r in near.collect()} >= {a for a in fps for b in fps if a != b and (a ^ b).bit_count() <= 3}
    got = {r.node % 2**64: r.root % 2**64 for r in components(links(near), "a", "b").collect()}
    groups = lambda m: {frozenset(k for k in m if m[k] == v) for v in set(m.values())}
    assert {g for g in groups(got)} == {g for g in groups(want) if len(g) > 1}


def test_components_of_a_chain_and_a_star(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 30)] + [(5, 5), (7, 6)]
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "a long, b long"), "a", "b").collect()}
    assert got == {**{i: 0 for i in range(41)}, **{100 + i: 100 for i in range(30)}}
    assert components(spark.createDataFrame([], "a long, b long"), "a", "b").count() == 0


def test_edge_rows(spark):
    rows = [(3, None, 1), (1, "", 1), (None, "a b c d", 1), (9, "a b c d", 1), (9, "a b c d", 1), (4, "q " * 20000, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fp int")
    got = {(r.doc_id, r.component_id) for r in near_groups(docs).collect()}
    assert got == {(3, 1), (1, 1), (None, 9), (9, 9), (4, 4)}
    assert near_groups(docs).count() == 6 and near_groups(docs.limit(0)).count() == 0
    kept = deduplicate(docs)
    assert kept.columns == docs.columns and sorted((r.doc_id or 0) for r in kept.collect()) == [0, 1, 4, 9]
