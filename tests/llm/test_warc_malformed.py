import gzip
import zlib

from certsel.llm import warc


def test_malformed_records_are_skipped_and_counted(spark, tmp_path):
    good = [warc.response(k, f"http://{k}/", f"<p>page {k}</p>") for k in range(4)]
    no_length = good[1].replace(b"Content-Length", b"Content-Size", 1) if good[1].count(b"Content-Length") == 1 else b"WARC/1.0\r\nWARC-Type: response\r\nWARC-Record-ID: <x>\r\n\r\nblock\r\n\r\n"
    no_id = b"WARC/1.0\r\nWARC-Type: response\r\nContent-Length: 5\r\n\r\nblock\r\n\r\n"
    odd = b"WARC/1.0\r\nWARC-Type: response\r\nWARC-Record-ID: <y>\r\nContent-Length: -3\r\n\r\n"
    (tmp_path / "a.warc").write_bytes(good[0] + no_length + no_id + odd + good[2] + good[3][:-20])
    (tmp_path / "b.warc.gz").write_bytes(gzip.compress(good[1]) + gzip.compress(good[3])[:60])
    (tmp_path / "c.warc").write_bytes(b"WARC/1.0\r\nWARC-Type: response")
    (tmp_path / "d.warc").write_bytes(b"")
    rows = warc.read_responses(spark, str(tmp_path)).collect()
    assert sorted(r.target_uri for r in rows if not r.error) == ["http://0/", "http://1/", "http://2/"]
    assert sum(bool(r.error) for r in rows) >= 5
    assert warc.convert(warc.read_responses(spark, str(tmp_path))).count() == 6


def test_empty_folder(spark, tmp_path):
    (tmp_path / "sub").mkdir()
    read = warc.read_responses(spark, str(tmp_path))
    assert read.count() == 0 and warc.convert(read).count() == 0


def test_letters_that_grow_when_lower_cased():
    page = "\u0130" * 12 + "<script>x</script>after<title>T\u0130tle</title><p>end"
    assert warc.text_and_links(page) == ("T\u0130tle", "\u0130" * 12 + "after\nT\u0130tle\nend", [])


def test_codings():
    text = "<p>caf\u00e9</p>"
    latin = text.encode("latin-1")
    head = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=ISO-8859-1"
    assert warc.payload(head, latin) == text
    assert warc.payload(head + b"\r\nContent-Encoding: gzip", gzip.compress(latin)) == text
    assert warc.payload(head + b"\r\nContent-Encoding: deflate", zlib.compress(latin)) == text
    assert warc.payload(head + b"\r\nTransfer-Encoding: chunked", b"5\r\n" + latin[:5] + b"\r\n%x;x=1\r\n" % len(latin[5:]) + latin[5:] + b"\r\n0\r\n\r\n") == text
    assert warc.payload(b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=none-such", text.encode()) == text
