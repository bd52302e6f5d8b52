"""SimHash fingerprints of 3-word shingles and near-duplicate groups by meet-in-the-middle ball hashing.

Two fingerprints within distance 3 share a point that lies within distance 1 of one and 2 of the other.  Emitting
the whole radius-2 ball of every fingerprint would shuffle about a thousand rows each, so two steps do it:

1. The 64 bits are cut into four blocks.  Two different fingerprints within distance 3 differ in some block; without
   that block they differ in 2 bits at most, so their radius-1 balls over the remaining 48 bits meet.  Each
   fingerprint emits those 4 x 49 variants; one that shares no variant with another fingerprint has no partner.
2. The rest emit their radius-1 ball (inner points) and the radius-2 points of their outer ball.  Two of any three
   differing bits lie in the same half of the word, so outer points flip two bits of one half: 2 x 496 of 2,016.
   Any inner member of a point is within 3 of every member, so linking all members to one inner member loses no
   link and makes no pairs within a group.
"""

from __future__ import annotations

from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, staged, tidy
from .components import components

RADIUS = 3
BITS = 64
SEED = 42


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """Unsigned 64-bit fingerprint.  A bit is set if it is set in over half of the shingle hashes; no words: zero."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z only, and the six ASCII blanks
    if not words:
        return 0
    rows = zip(*(words[i:] for i in range(shingle))) if len(words) >= shingle else [words]
    hashes = np.fromiter(map(xxhash.xxh64_intdigest, map(b" ".join, rows), repeat(SEED)), dtype="<u8")
    ones = np.zeros(BITS, dtype=np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = hashes[at:at + (1 << 16)]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp long).  fp is the fingerprint as a signed long.  Null texts count as empty; null ids pass through."""

    def run(batches):
        for b in batches:
            fps = np.array([fingerprint(t.as_py()) for t in b.column(1)], dtype="<u8").view("<i8")
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps, pa.int64())], names=["doc_id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(
        tidy(run), "doc_id long, fp long")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _longs(values) -> str:
    return "array(" + ",".join("(-9223372036854775807L - 1L)" if v == -(1 << 63) else f"{v}L" for v in map(_signed, values)) + ")"


def colliding(fps: DataFrame) -> DataFrame:
    """Of distinct fingerprints, those that share a radius-1 variant over 48 bits with another one (no partner is lost)."""
    singles = [0, *(1 << i for i in range(BITS))]
    keeps = [((1 << 64) - 1) ^ (0xFFFF << (16 * j)) for j in range(4)]
    rows = fps.select("fp", F.explode(F.expr(_longs(keeps))).alias("keep"))
    rows = rows.select("fp", "keep", F.explode(F.expr(_longs(singles))).alias("flip")).where("flip & keep = flip")
    rows = rows.select("fp", F.expr("(fp & keep) ^ flip").alias("point"))
    w = Window.partitionBy("point").orderBy("fp")
    met = rows.select("fp", F.lag("fp").over(w).alias("p"), F.lead("fp").over(w).alias("n"))
    return met.where("p <> fp or n <> fp").select("fp").distinct()


def links(fps: DataFrame) -> DataFrame:
    """(a, b) links of distinct fingerprints whose components equal those of all pairs within distance 3."""
    inner = [0, *(1 << i for i in range(BITS))]
    outer = [(1 << i) | (1 << j) for half in (range(32), range(32, 64)) for i, j in combinations(half, 2)]
    rows = fps.select("fp", F.explode(F.expr(_longs(inner + outer))).alias("flip"))
    rows = rows.select("fp", F.expr("fp ^ flip").alias("point"), F.expr("bit_count(flip) < 2").alias("inner"))
    w = Window.partitionBy("point").orderBy(F.desc("inner"), "fp")
    met = rows.select("fp", F.first("fp").over(w).alias("rep"), F.first("inner").over(w).alias("rep_inner"))
    return (met.where("rep_inner and fp <> rep").select(F.col("fp").alias("a"), F.col("rep").alias("b")).distinct()
            .where(f"bit_count(a ^ b) <= {RADIUS}"))


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable).

    Empty and null texts have fingerprint zero and are linked like any other.  Repeated rows come back as often as
    they came; a group whose ids are all null has a null component_id.  An empty table gives no rows.
    """
    fps, _ = staged(fingerprints(docs, id_col, text_col), "fingerprints")
    known, known_path = staged(fps.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    close, close_path = staged(colliding(known), "colliding")
    found = components(links(close), "a", "b")
    grouped = known.join(found, known.fp == found.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    ids = grouped.groupBy("root").agg(F.min("least").alias("component_id"))
    named, _ = staged(grouped.join(ids, "root").select("fp", "component_id"), "groups")
    discard(docs.sparkSession, known_path, close_path)
    return fps.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Keep one document of each group: the one with the smallest id.

    Rows whose id is null have no rank in a group and are kept.  Of several rows with the kept id, all identical ones
    collapse to one and different ones stay.
    """
    groups = near_groups(docs, id_col, text_col).where("component_id = doc_id").select(F.col("doc_id").alias(id_col)).distinct()
    kept = docs.where(F.col(id_col).isNotNull()).join(groups, id_col, "left_semi")
    return kept.dropDuplicates(docs.columns).unionByName(docs.where(F.col(id_col).isNull()))
