import hashlib
import random
import re

from certsel.llm import pii
from hypothesis import given, settings
from hypothesis import strategies as st

PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def luhn(d):
    return sum(x if i % 2 == 0 else x * 2 - 9 * (x > 4) for i, x in enumerate(map(int, reversed(d)))) % 10 == 0


def base(text):
    out = []
    for kind, pattern in PLAIN.items():
        for m in re.finditer(pattern, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            ok = {"email": True, "ip": kind != "ip" or all(int(p) <= 255 for p in m[0].split(".")), "card": 16 <= len(d) <= 19 and luhn(d), "phone": 8 <= len(d) <= 15}[kind]
            if ok:
                out.append((kind, m.start(), m.end()))
    return out


def spans_of(spark, texts):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return {r.doc_id: r for r in pii.report(df).collect()}


def holds(got, texts):
    for k, t in enumerate(texts):
        want = base(t)
        joined = ",".join(f"{a}:{b}:{c}" for a, b, c in want)
        r = got[k]
        assert r.base_sha256 == hashlib.sha256(joined.encode()).hexdigest(), (t, want, r.spans)
        assert [r[f"n_{x}"] for x in PLAIN] == [sum(s[0] == x for s in want) for x in PLAIN]
        assert set(joined.split(",")) - {""} <= set(r.spans.split(","))


def test_documents(spark, sf):
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("text").collect()
    texts = [r.text for r in rows]
    holds(spans_of(spark, texts), texts)


def test_random_texts(spark):
    rng = random.Random(9)
    parts = ["4111111111111111", "4111-1111 1111 1111", "+1 (555) 123-4567", "a@b.co", "_@x-y.z1.q", "@", ".", "..", "10.0.0.255", "256.1.1.1", "1.2.3.4.5.6.7.8", " ", "-", "\n", "é", "\U0001f600",
             "7", "42", "+", "a.b@c.d@e.f", "(", ")", "000.00.1.01", "x_y%z+1@h.io", "12 34 56 78 90 12 34 56", "--", "\U00010400"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(1, 14))) for _ in range(400)]
    texts += ["".join(rng.choice("0123456789- .+@a") for _ in range(60)) for _ in range(400)]
    holds(spans_of(spark, texts), texts)


def test_edges_and_long_texts(spark):
    texts = [None, "", "7" * 200_000, "a" * 200_000, "1." * 8_000, "+" * 50_000, "1." * 50_000, "a@b.co " * 3000, "x " * 100_000 + "é me@here.org"]
    holds(spans_of(spark, texts), texts)
    df = spark.createDataFrame([], "doc_id long, text string, spans int")
    assert pii.report(df).count() == 0


def test_added_kinds_and_scores(spark):
    got = spans_of(spark, ["My IBAN is GB82 WEST 1234 5698 7654 32.", "IBAN GB82 WEST 1234 5698 7654 33.", "his social security number: 123-45-6789", "part 123-45-6789", "mail me: a@b.co", "a@b.co"])
    assert got[0].spans == "iban:11:38" and got[1].spans == "" and got[2].spans == "ssn:28:39" and got[3].spans == ""
    assert got[4].max_score > got[5].max_score


def test_only_native_operators(spark, sf):
    plan = pii.report(spark.read.parquet(f"{sf}/documents.parquet"))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)
