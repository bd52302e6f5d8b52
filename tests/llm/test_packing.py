import zlib

import numpy as np
import public_tokenizers
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from certsel.llm.packing import DotProductPacker, Limits, pack_documents, pack_examples
from certsel.llm.tokens import TokenIds

PATH = public_tokenizers.path("byte_bpe_50k.json")
IDS, LIBRARY = TokenIds(PATH), Tokenizer.from_file(PATH)


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet="ab'stvelrdm 12_.,\n\t\r\xa0\x1c\x85½éß日ª́", max_size=40))
def test_ids_agree_with_the_library(text):
    assert np.frombuffer(IDS.encode(text), "<u4").tolist() == LIBRARY.encode(text, add_special_tokens=False).ids


def test_special_token_strings_follow_the_library():
    text = "a <|endoftext|> b"
    assert np.frombuffer(IDS.encode(text), "<u4").tolist() == LIBRARY.encode(text, add_special_tokens=False).ids


def check_pieces(rows, texts):
    want = {k: LIBRARY.encode(t or "", add_special_tokens=False).ids + [0] for k, t in texts.items()}
    for k, ids in want.items():
        at = 0
        for r in sorted((r for r in rows if r.doc_id == k), key=lambda r: r.start):
            part = np.array(ids[r.start:r.start + r.length], dtype="<u4")
            assert (r.start, r.doc_tokens, r.ids_crc32) == (at, len(ids), zlib.crc32(part.tobytes()))
            at += r.length
        assert at == len(ids)
    by_seq = {}
    for r in rows:
        by_seq.setdefault(r.sequence_id, []).append(r)
    for pieces in by_seq.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 1024
    used = sum(r.length for r in rows)
    return used, len(by_seq)


def test_round_trip_and_little_padding(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
    used, sequences = check_pieces(pack_documents(docs, PATH).collect(), texts)
    assert used / (sequences * 1024) > 0.98


def test_edge_documents(spark):
    texts = {1: None, 2: "", 3: "x", 4: "word " * 5000, 5: "x"}
    docs = spark.createDataFrame([(k, t, "s", 1) for k, t in texts.items()], "doc_id long, text string, sequence_id string, start int").coalesce(1)
    check_pieces(pack_documents(docs, PATH).collect(), texts)
    assert pack_documents(docs.limit(0), PATH).count() == 0
    limited = pack_documents(docs, PATH, limits=Limits(segments=2)).groupBy("sequence_id").count()
    assert max(r["count"] for r in limited.collect()) <= 2


def test_examples_keep_all_limits(spark):
    rng = np.random.default_rng(1)
    rows = [(i, int(rng.integers(1, 90)), int(rng.integers(0, 60))) for i in range(600)] + [(900, 101, 5), (901, None, 1), (902, 0, 0), (902, 0, 0)]
    limits = Limits(tokens=100, segments=4, loss_tokens=80, open_bins=8)
    out = pack_examples(spark.createDataFrame(rows, "id long, tokens int, loss int"), "id", "tokens", "loss", limits).collect()
    assert sorted(r.id for r in out) == sorted(r[0] for r in rows)
    assert {r.id for r in out if r.sequence_id is None} == {900, 901}
    bins = {}
    for r in out:
        if r.sequence_id is not None:
            bins.setdefault(r.sequence_id, []).append(r)
    for items in bins.values():
        assert sum(r.tokens for r in items) <= 100 and len(items) <= 4 and sum(r.loss_tokens for r in items) <= 80


def test_dot_product_choice():
    p = DotProductPacker(Limits(tokens=100, segments=10, loss_tokens=100, open_bins=4))
    p.place("a", 60, 10)
    p.new()
    p.put(1, "b", np.array([10, 1, 60]))
    # Room (40, 9, 90) against (90, 9, 40): an example heavy in loss goes where loss room is left.
    assert p.best(np.array([5, 1, 35])) == 0 and p.best(np.array([35, 1, 5])) == 1
    assert p.best(np.array([50, 1, 50])) == -1
