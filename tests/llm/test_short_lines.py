import random

from certsel.llm import lines

K, SIMILARITY = 5, 0.8  # what the operator promises, not what it is set to


def similar(a, b):
    x, y = ({line[i:i + K] for i in range(len(line) - K + 1)} for line in (a, b))
    return len(x & y) >= SIMILARITY * len(x | y)


def test_typos_in_ordinary_lines(spark):
    rng = random.Random(5)
    rows, want = [], {}
    for k in range(60):
        n = rng.randint(30, 100)
        line = "".join(rng.choice("abcdefghijklmnopqrstuvw ") for _ in range(n - 2)).join("xy")
        at = rng.randrange(n)
        copy = line[:at] + "9" + line[at + 1:]
        rows += [(2 * k, line), (2 * k + 1, copy)]
        want |= {2 * k: line, 2 * k + 1: "" if similar(line, copy) else copy}
    assert sum(t == "" for t in want.values()) > 30 and sum(len(t) < 50 for t in want.values() if t) > 5
    got = lines.deduplicate_lines(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r.doc_id: r.text for r in got.collect()} == want
