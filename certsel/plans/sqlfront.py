"""A statement form of a selection: a table-function call with named arguments.

    SELECT * FROM certified_select(source => 'rare', goal => 'recall', level => 95, confidence => 95, labels => 10000)

source is a registered workload, or a table or view with keep => '<SQL predicate>', score => '<SQL expression in [0, 1]>' and
key => '<column>'.  Levels above 1 are percent.  Other arguments: method, mix, exponent, step, seed, bound.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from certsel.functions.synth import quantised
from certsel.operators import runner
from certsel.sources.workloads import ALL
from certsel.spec import SelectionSpec

_TOKEN = re.compile(r"\s*(?:(?P<word>[A-Za-z_][A-Za-z_0-9]*)|(?P<number>[0-9]+(?:\.[0-9]+)?)|'(?P<text>(?:[^']|'')*)'|(?P<sign>=>|[(),*;]))")
_CALL = "certified_select"


def _tokens(statement: str) -> list[tuple[str, str]]:
    out, at = [], 0
    text = statement.rstrip()
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise ValueError(f"cannot read the statement at {text[at:at + 20]!r}")
        kind = m.lastgroup
        out.append((kind, m[kind].replace("''", "'") if kind == "text" else m[kind]))
        at = m.end()
    return out


def parse(statement: str) -> tuple[dict, SelectionSpec]:
    """(source arguments, specification)."""
    tokens = [t for t in _tokens(statement) if t != ("sign", ";")]
    head = [("word", "select"), ("sign", "*"), ("word", "from"), ("word", _CALL), ("sign", "(")]
    if [(k, v.lower()) for k, v in tokens[:5]] != head or not tokens[5:] or tokens[-1] != ("sign", ")"):
        raise ValueError(f"expected SELECT * FROM {_CALL}(name => value, ...)")
    args, rest = {}, tokens[5:-1]
    for i in range(0, len(rest), 4):
        part = rest[i:i + 4]
        if len(part) < 3 or part[0][0] != "word" or part[1][1] != "=>" or (len(part) == 4 and part[3][1] != ","):
            raise ValueError("expected name => value, separated by commas")
        name, (kind, value) = part[0][1].lower(), part[2]
        if name in args:
            raise ValueError(f"{name} is given twice")
        args[name] = float(value) if kind == "number" else value
    share = lambda x: x / 100 if x > 1 else x
    for needed in ("source", "goal", "level", "labels"):
        if needed not in args:
            raise ValueError(f"{needed} is missing")
    source = {k: args.pop(k) for k in ("source", "keep", "score", "key") if k in args}
    goal, level, budget = args.pop("goal"), share(args.pop("level")), int(args.pop("labels"))
    settings = {"target": level, "delta": round(1 - share(args.pop("confidence", 0.95)), 12), "budget": budget, "goal": goal,
                "method": args.pop("method", "weighted" if goal == "recall" else "twostage")}
    for name, kind in (("mix", float), ("exponent", float), ("step", int), ("seed", int), ("bound", str)):
        if name in args:
            settings[name] = kind(args.pop(name))
    if args:
        raise ValueError(f"unknown arguments: {sorted(args)}")
    return source, SelectionSpec(**settings)


def execute(spark: SparkSession, statement: str, sf_dir: str | None = None) -> DataFrame:
    source, spec = parse(statement)
    if source["source"] in ALL and "keep" not in source:
        w = ALL[source["source"]]
        return runner.run(w.scored(spark, sf_dir), w.oracle, spec).rows
    table = spark.table(source["source"])
    base = table.withColumn("key", F.expr(source["key"])).withColumn("score_u", quantised(F.expr(source["score"]).cast("double")))
    return runner.run(base, lambda df: df.withColumn("y", F.coalesce(F.expr(source["keep"]), F.lit(False)).cast("int")), spec).rows.select(*table.columns)
