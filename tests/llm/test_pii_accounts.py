from certsel.llm import pii

DE, GB, NO = "DE89370400440532013000", "GB82 WEST 1234 5698 7654 32", "NO9386011117947"


def test_accounts_inside_sentences(spark):
    cases = [(f"IBAN {DE} Please pay", [DE]), (f"IBAN {GB} EUR 50", [GB]), (f"bank: {GB} AND {NO} 12 days", [GB, NO]), (f"account {DE} {GB}", [DE, GB]),
             (f"bank AB12 {DE} X", [DE]), (f"bank {DE}x", []), (f"bank {DE}0", []), (f"bank {NO} OR PAY CASH 100 200 300 400 500 600", [NO]), (f"bank é\U0001f600 {GB}", [GB]),
             ("bank " + "AB12 " * 2000 + f"{DE} Now", [DE]), ("bank AB12" + "A" * 100_000, [])]
    df = spark.createDataFrame([(k, t) for k, (t, _) in enumerate(cases)], "doc_id long, text string")
    got = {r.doc_id: r.spans for r in pii.report(df).collect()}
    for k, (text, numbers) in enumerate(cases):
        want = ",".join(f"iban:{text.index(n)}:{text.index(n) + len(n)}" for n in numbers)
        assert ",".join(s for s in got[k].split(",") if s.startswith("iban")) == want, (text[:80], got[k][:200])
