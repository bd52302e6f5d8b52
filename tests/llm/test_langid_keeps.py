from certsel.llm import common, langid


def test_every_named_document_stays(spark, sf):
    docs = common.table(spark, sf, "documents").select("doc_id", "text", "lang")
    model = langid.train(docs)
    parts = {}
    for r in docs.where("length(text) > 400").collect():
        parts.setdefault(r.lang, r.text[:300])
    texts = [" ".join(parts[x][k:k + 300 // len(parts)] for x in sorted(parts)) for k in range(0, 60, 3)]
    texts += [w for t in parts.values() for w in t.split()[:20]] + [None, "", "12 34", "..."]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = langid.predict(rows, model).collect()
    named = {r.doc_id for r in found if r.lang_pred != langid.UNDETERMINED}
    assert any(r.score < 0.5 for r in found if r.doc_id in named)
    assert {r.doc_id for r in langid.keep_determined(rows, model).collect()} == named
