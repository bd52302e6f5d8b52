from certsel.llm import packing, queries
from certsel.llm.tokens import TokenIds


def test_limits_hold_and_nothing_is_lost(spark, sf):
    turns = spark.read.parquet(f"{sf}/conversations.parquet")
    ids, want = TokenIds(queries.tokenizer_path()), {}
    for r in turns.collect():
        n = len(ids.encode(r.text or "")) // 4
        tokens, loss = want.get(r.conv_id, (0, 0))
        want[r.conv_id] = tokens + n, loss + n * (r.role == "assistant")
    rows = queries.packed_conversations(spark, sf).collect()
    assert {r.id: (r.tokens, r.loss_tokens) for r in rows} == want and len(rows) == len(want)
    limits, bins = packing.Limits(tokens=4096, segments=8, loss_tokens=1024), {}
    for r in rows:
        fits = r.tokens <= limits.tokens and r.loss_tokens <= limits.loss_tokens
        assert (r.sequence_id is not None) == fits
        if fits:
            bins.setdefault(r.sequence_id, []).append(r)
    for items in bins.values():
        items.sort(key=lambda r: r.segment)
        assert [r.segment for r in items] == list(range(len(items))) and len(items) <= limits.segments
        assert [r.offset for r in items] == [sum(x.tokens for x in items[:k]) for k in range(len(items))]
        assert sum(r.tokens for r in items) <= limits.tokens and sum(r.loss_tokens for r in items) <= limits.loss_tokens


def test_null_and_empty(spark):
    turns = spark.createDataFrame([(1, "assistant", None), (None, "user", "hello"), (2, "user", "")], "conv_id long, role string, text string")
    got = {r.id: (r.tokens, r.loss_tokens) for r in packing.pack_conversations(turns, queries.tokenizer_path()).collect()}
    assert got[1] == (0, 0) and got[2] == (0, 0) and got[None][0] > 0
    assert packing.pack_conversations(turns.limit(0), queries.tokenizer_path()).count() == 0


def test_one_very_long_text(spark):
    docs = spark.createDataFrame([(1, "ab" * 300_000), (2, "x")], "doc_id long, text string")
    rows = sorted(packing.pack_documents(docs, queries.tokenizer_path()).where("doc_id = 1").collect(), key=lambda r: r.start)
    assert [r.start for r in rows] == [sum(x.length for x in rows[:k]) for k in range(len(rows))] and sum(r.length for r in rows) == rows[0].doc_tokens
