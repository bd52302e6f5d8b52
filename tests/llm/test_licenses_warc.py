import base64
import hashlib
import html
import json
import re

from certsel.llm import licenses, warc


def test_known_texts_in_other_dress(spark):
    mit = licenses.KNOWN["MIT"]
    rows = [(1, mit), (2, "Copyright (c) 2020 Some One\n" + mit.upper()), (3, mit.replace(" ", "  \t").replace(",", " -- ")), (4, mit + " extra"), (5, None), (6, ""), (7, "...\n--"),
            (8, "Released under the MIT Licence!"), (None, mit), (1, mit), (9, "word " * 30000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "1 as digest", "'x' as license_id")
    out = licenses.scan(df).collect()
    assert len(out) == len(rows)
    found = {(r.doc_id, r.license_id) for r in out}
    assert found == {(1, "MIT"), (2, "MIT"), (3, "MIT"), (4, None), (5, None), (6, None), (7, None), (8, "notice-MIT"), (None, "MIT"), (9, None)}
    assert {r.digest for r in out if r.doc_id in (5, 6, 7)} == {hashlib.sha256(b"").hexdigest()}
    assert licenses.scan(df.limit(0)).count() == 0


def test_expression_agrees_with_python(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r.doc_id: r.digest for r in licenses.scan(docs).collect()}
    assert got == {r.doc_id: licenses.digest_of(r.text or "") for r in docs.collect()}
    assert len({licenses.digest_of(t) for t in licenses.KNOWN.values()}) == len(licenses.KNOWN)


def plain_text(page):
    page = re.sub(r"(?is)<!--.*?(-->|$)", "", page)
    page = re.sub(r"(?is)<(script|style|noscript|template)\b[^>]*>.*?(?=</\1|$)", "", page)
    page = re.sub(r"(?is)</?(%s)(?=[\s>/])[^>]*>?" % "|".join(warc.BLOCKS), "\n", page)
    page = re.sub(r"(?s)<[a-zA-Z/!?][^>]*>?", "", page)
    return "\n".join(x for x in (" ".join(l.split()) for l in html.unescape(page).split("\n")) if x)


def test_records(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    source = {r.page_id: r for r in pages.collect()}
    out = warc.derivatives(pages).collect()
    assert len(out) == 2 * len(source)
    for r in out:
        page = source[r.page_id]
        (headers, block), = warc.parse(bytes(r.record))
        (sh, sb), = warc.parse(warc.response(page.page_id, page.url, page.html))
        assert headers["WARC-Type"] == r.record_type and headers["WARC-Refers-To"] == r.refers_to == sh["WARC-Record-ID"] and headers["WARC-Target-URI"] == page.url
        assert r.block_digest == headers["WARC-Block-Digest"] == "sha1:" + base64.b32encode(hashlib.sha1(block).digest()).decode()
        assert r.source_payload_digest == sh["WARC-Payload-Digest"] and r.source_block_digest == sh["WARC-Block-Digest"] and len(block) == r.block_length
        if r.record_type == "conversion":
            assert block.decode() == plain_text(page.html)
        else:
            meta = json.loads(block)
            assert meta["warc-headers"] == sh and meta["payload"]["length"] == len(page.html.encode()) and meta["http"]["headers"]["Content-Type"].startswith("text/html")
            assert meta["html"]["links"][:3] == [html.unescape(x) for x in re.findall(r'<a href="([^"]*)"', page.html)][:3]


def test_files_and_edges(spark, tmp_path):
    pages = [(1, "http://a/", "<p>One &amp; two<br>three</p>"), (2, None, None), (3, "http://b/", "<script>var x='</p>'; never closed"), (4, "u", "a <!-- open"), (5, "u", "<" * 3000)]
    (tmp_path / "x.warc.gz").write_bytes(b"".join(warc.gzipped(warc.response(i, u or "", h or "")) for i, u, h in pages))
    read = warc.read_responses(spark, str(tmp_path))
    assert read.count() == 5
    df = spark.createDataFrame(pages + [pages[0]], "page_id long, url string, html string").selectExpr("*", "1 as record_id")
    one = warc.derivatives(df).collect()
    assert len(one) == 12
    assert {bytes(r.record) for r in one} == {bytes(r.record) for r in warc.convert(read).collect()}
    texts = {(r.page_id): list(warc.parse(bytes(r.record)))[0][1].decode() for r in one if r.record_type == "conversion"}
    assert texts[1] == "One & two\nthree" and texts[2] == "" and texts[3] == "" and texts[4] == "a"
    assert warc.derivatives(df.limit(0)).count() == 0
