"""Personal data by pattern, checksum and context, in DataFrame functions only.

Regular expressions propose spans; validators confirm them (address parts, Luhn, digit counts, mod 97); words near a span
raise or lower its score.  Base kinds stay whatever their score; kinds the method adds are kept from a minimum score.

Positions come from splitting a text at the matches: a match starts after all pieces and matches before it.  Patterns are
possessive and start only where a run of their characters starts, so that each text is read in linear time.  They match
what the plain forms match, leftmost and without overlap; for cards, those of the plain matches that have 16 to 19 digits.
Account numbers differ: a match is a country code alone, and what follows is seen ahead.  Each of its ends at a token's end
is tried, so that words or numbers after an account number do not hide it, nor one account number the next.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty

# The kinds, in the order in which spans are listed.
BASE_KINDS = ("email", "ip", "card", "phone")
ADDED_KINDS = ("iban", "ssn")

_LOCAL = "[A-Za-z0-9._%+-]"


@dataclass(frozen=True)
class Kind:
    pattern: str
    hint: str  # a cheap test that every text with a match passes
    prior: float
    words: str  # context that raises the score


KINDS = {
    "email": Kind(rf"(?:\G|(?<!{_LOCAL})){_LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "@", 0.9, "mail|contact|write|reach"),
    "ip": Kind(r"(?<![0-9])[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)", ".", 0.6, "ip|address|host|server|login"),
    "card": Kind(r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){15,18}+(?![\x20-]?[0-9])", "", 0.8, "card|visa|credit|payment|account"),
    "phone": Kind(r"\+[0-9][\x20().0-9-]+[0-9]", "+", 0.7, "phone|tel|call|mobile|fax"),
    # The last sign, if any, shows that the token goes on: no end there.
    "iban": Kind(r"(?<![A-Za-z0-9])[A-Z]{2}(?=([0-9]{2}(?:\x20?[A-Z0-9]){11,30}+[A-Za-z0-9]?+))", "", 0.7, "iban|bank|account|transfer"),
    "ssn": Kind(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])", "-", 0.3, "ssn|social|security"),
}
#: Lengths by country only choose between several ends that pass; other countries and lengths are found too.
IBAN_LENGTHS = {n: codes.split() for n, codes in {
    15: "NO", 16: "BE", 18: "DK FI FO GL NL", 19: "MK SI", 20: "AT BA EE KZ LT LU XK", 21: "CH HR LI LV", 22: "BG BH CR DE GB GE IE ME RS VA",
    23: "AE GI IL IQ TL", 24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "PT", 26: "IS TR", 27: "FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HU LB PL",
    29: "BR EG PS QA UA", 30: "JO KW MU", 31: "MT SC", 32: "LC"}.items()}
CONTEXT_CHARS = 40
MIN_SCORE = 0.6


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _luhn(m: Column) -> Column:
    """True if the digits of m pass: every second one from the right is doubled, less nine if above nine."""
    d = F.reverse(_digits(m))
    chars = F.split(d, "")
    total = F.aggregate(F.transform(chars, lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(
        F.when(c.cast("int") > 4, c.cast("int") * 2 - 9).otherwise(c.cast("int") * 2))), F.lit(0), lambda a, x: a + x)
    return total % 10 == 0


def _mod97(m: Column) -> Column:
    """True if the account number, its first four signs moved to the end and letters read as 10 to 35, is 1 mod 97."""
    s = F.regexp_replace(m, r"\x20", "")
    turned = F.concat(F.substring(s, 5, 100), F.substring(s, 1, 4))
    value = lambda c: F.when(c >= "A", F.ascii(c) - 55).otherwise(F.ascii(c) - 48)
    step = lambda a, c: F.when(value(c) > 9, (a * 100 + value(c)) % 97).otherwise((a * 10 + value(c)) % 97)
    return F.aggregate(F.split(turned, ""), F.lit(0), step) == 1


def _confirmed(kind: str, m: Column) -> Column:
    n = F.length(_digits(m))
    return {
        "email": lambda: F.lit(True),
        "ip": lambda: F.forall(F.split(m, r"\."), lambda p: (F.length(F.regexp_replace(p, "^0+", "")) <= 3) & (
            F.coalesce(F.substring(F.regexp_replace(p, "^0+(?=.)", ""), 1, 4).cast("int"), F.lit(0)) <= 255)),
        "card": lambda: n.between(16, 19) & _luhn(F.substring(m, 1, 40)),
        "phone": lambda: n.between(8, 15),
        "iban": lambda: F.length(F.regexp_replace(m, r"\x20", "")).between(15, 34) & _mod97(m),
        "ssn": lambda: ~F.substring(m, 1, 3).isin("000", "666") & (F.substring(m, 1, 1) != "9"),
    }[kind]()


def _account(m: Column) -> Column:
    """The prefix of m, cut at a token's end, that passes; of several the one of its country's length, else the longest; or null."""
    tokens = F.split(m, " ")
    ends = F.transform(F.sequence(F.lit(1), F.size(tokens)), lambda n: F.array_join(F.slice(tokens, F.lit(1), n), " "))
    good = F.filter(ends, lambda e: e.rlike(r"^[A-Z0-9\x20]+$") & _confirmed("iban", e))
    n = lambda e: F.length(F.regexp_replace(e, r"\x20", ""))
    usual = lambda e: reduce(Column.__or__, [(n(e) == size) & F.substring(e, 1, 2).isin(*codes) for size, codes in IBAN_LENGTHS.items()])
    return F.array_max(F.transform(good, lambda e: F.struct(usual(e).alias("usual"), n(e).alias("n"), e.alias("m"))))["m"]


def _accounts(heads: Column, text: Column) -> Column:
    """heads: (m, s) of the country codes.  (m, s) of the account numbers, leftmost first and without overlap."""
    ahead = F.regexp_extract_all(text, F.lit(KINDS["iban"].pattern), F.lit(1))
    whole = F.filter(F.zip_with(heads, ahead, lambda h, t: F.struct(_account(F.concat(h["m"], t)).alias("m"), h["s"].alias("s"))), lambda x: x["m"].isNotNull())
    state = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<struct<m:string,s:int>>)").alias("out"))
    return F.aggregate(whole, state, lambda a, x: F.when(x["s"] < a["at"], a).otherwise(F.struct(
        (x["s"] + F.length(x["m"])).alias("at"), F.concat(a["out"], F.array(x)).alias("out"))), lambda a: a["out"])


def _spans(kind: str, text: Column) -> Column:
    """Array of (kind, start, end, score) of one kind, in order; end exclusive, in code points."""
    k = KINDS[kind]
    found = F.regexp_extract_all(text, F.lit(k.pattern), F.lit(0))
    pieces = F.split(text, k.pattern, -1)
    state = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<struct<m:string,s:int>>)").alias("out"))
    walked = F.aggregate(F.zip_with(found, F.slice(pieces, 1, F.size(found)), lambda m, p: F.struct(m.alias("m"), p.alias("p"))), state,
                         lambda a, x: F.struct((a["at"] + F.length(x["p"]) + F.length(x["m"])).alias("at"),
                                               F.concat(a["out"], F.array(F.struct(x["m"].alias("m"), (a["at"] + F.length(x["p"])).alias("s")))).alias("out")),
                         lambda a: a["out"])
    kept = _accounts(walked, text) if kind == "iban" else F.filter(walked, lambda x: _confirmed(kind, x["m"]))
    # The characters before and after the span, without it: what it is made of says nothing about it.
    ahead = lambda x: F.substring(text, F.greatest(F.lit(1), x["s"] + 1 - CONTEXT_CHARS), F.least(x["s"], F.lit(CONTEXT_CHARS)))
    behind = lambda x: F.substring(text, x["s"] + 1 + F.length(x["m"]), F.lit(CONTEXT_CHARS))
    near = lambda x: F.lower(F.concat(ahead(x), F.lit(" | "), behind(x)))
    words = lambda w: rf"(?<![a-z0-9])(?:{w})(?![a-z0-9])"
    score = lambda x: F.least(F.lit(1.0), F.lit(k.prior) + F.when(near(x).rlike(words(k.words)), 0.3).otherwise(0.0)
                              - F.when(near(x).rlike(words("example|sample|version|test")), 0.2).otherwise(0.0))
    spans = F.transform(kept, lambda x: F.struct(F.lit(kind).alias("kind"), x["s"].alias("start"), (x["s"] + F.length(x["m"])).alias("end"), score(x).alias("score")))
    hint = F.contains(text, F.lit(k.hint)) if k.hint else text.rlike("[0-9]")
    return F.when(hint, spans).otherwise(F.expr("cast(array() as array<struct<kind:string,start:int,end:int,score:double>>)"))


def find(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, spans_found): array of (kind, start, end, score), by kind as listed and then start.

    Null and empty texts have none.  Repeated rows give equal rows; null ids pass through.  Spans of different kinds may
    overlap; those of one kind do not.
    """
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(F.col(text_col).cast("string")).alias("text"))
    cols = [_spans(k, F.col("text")).alias(f"s_{k}") for k in (*BASE_KINDS, *ADDED_KINDS)]
    s = d.select("doc_id", *cols)
    added = [F.filter(f"s_{k}", lambda x: x["score"] >= MIN_SCORE) for k in ADDED_KINDS]
    return s.select("doc_id", F.concat(*[F.col(f"s_{k}") for k in BASE_KINDS]).alias("base"), F.concat(*added).alias("added"))


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, max_score (null without spans)."""
    f = find(docs, id_col, text_col)
    f = f.select("doc_id", "base", F.concat("base", "added").alias("both"))
    of = lambda k: F.filter("base", lambda x: x["kind"] == k)
    counts = [F.size(of(k)).cast("long").alias(f"n_{k}") for k in BASE_KINDS]
    return f.select("doc_id", *counts, F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(F.col("both")).alias("spans"),
                    F.array_max(F.transform("both", lambda x: x["score"])).alias("max_score"))
