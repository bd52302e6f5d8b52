import random

from certsel.llm import lines
from test_lines import plain


def test_families_of_lines_too_unlike_to_link(spark):
    """Lines of one template share buckets without being similar; their near copies are found among them."""
    rng = random.Random(11)
    letters = "abcdefghijklmnopqrstuvwxyz "
    word = lambda n: "".join(rng.choice(letters) for _ in range(n))
    made = []
    for _ in range(3):
        template = word(90)
        for _ in range(60):
            line = template + "x" + word(28) + "y"
            at = rng.randrange(20, 70)
            made += [line, line[:at] + "9" + line[at + 1:]]
    rng.shuffle(made)
    docs = [(k, line) for k, line in enumerate(made)]
    want = plain(docs)
    assert 100 < sum(t == "" for t in want.values()) < 300
    got = {r.doc_id: r.text for r in lines.deduplicate_lines(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == want
