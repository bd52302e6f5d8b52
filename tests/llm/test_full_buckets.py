import random

from certsel.llm import lines
from test_lines import plain


def test_every_link_in_buckets_of_many_unlike_lines(spark):
    """One template, two copies of each line: no order of a bucket's rows brings all pairs together."""
    rng = random.Random(4)
    letters = "abcdefghijklmnopqrstuvwxyz "
    word = lambda n: "".join(rng.choice(letters) for _ in range(n))
    template, made = word(110), []
    for _ in range(500):
        line = template + "x" + word(38) + "y"
        at = rng.sample(range(20, 100), 2)
        made += [line, "".join("9" if k in at else c for k, c in enumerate(line))]
    rng.shuffle(made)
    docs = [(k, line) for k, line in enumerate(made)]
    want = plain(docs)
    assert 100 < sum(t == "" for t in want.values()) < 900
    got = {r.doc_id: r.text for r in lines.deduplicate_lines(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == want
