import textwrap

from certsel.llm import licenses


def test_known_texts_at_any_width(spark):
    rows = []
    for name, text in licenses.KNOWN.items():
        for width in (*range(20, 100, 3), 1000):
            wrapped = "\n\n".join(textwrap.fill(p, width) for p in text.split("\n\n"))
            rows += [(name, wrapped), (name, "Copyright 2020 Some One\n\n" + wrapped), (name, "Copyright Some One and others\n" + "\n".join(" * " + x for x in wrapped.split("\n")))]
    assert any(line.lower().startswith("copyright notice") for _, t in rows for line in t.split("\n"))
    got = licenses.scan(spark.createDataFrame([(k, t) for k, (_, t) in enumerate(rows)], "doc_id long, text string")).collect()
    assert {r.doc_id: r.license_id for r in got} == {k: name for k, (name, _) in enumerate(rows)}
    assert all(r.digest == licenses.digest_of(rows[r.doc_id][1]) for r in got)
