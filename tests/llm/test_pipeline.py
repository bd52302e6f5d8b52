import corpus_pipeline as cp
from certsel.llm import common, langid, mixing


def test_stages(spark, sf):
    docs = common.table(spark, sf, "documents")
    kept = [docs]
    for name, stage in cp.STAGES:
        out, _ = common.staged(stage(spark, kept[-1], sf), "test")
        kept.append(out)
    _, lang, lines, near, mix, packed = kept
    assert all(k.columns == docs.columns for k in (lang, lines, near, mix))
    assert lang.count() >= 0.95 * docs.count()
    ids = lambda d: {r.doc_id for r in d.select("doc_id").collect()}
    assert ids(near) <= ids(lines) <= ids(lang) and ids(mix) <= ids(near) and ids(packed) == ids(mix)
    assert not lines.where("text = ''").count() or docs.where("text = ''").count()
    plan = {r.doc_id: r for r in mixing.allocate(near).collect()}
    copies = {r.doc_id: r["count"] for r in mix.groupBy("doc_id").count().collect()}
    assert all(copies.get(k, 0) == (1 if r.size == 0 else int(r.taken / r.size + 0.5)) for k, r in plan.items())
