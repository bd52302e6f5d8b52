"""Removal of fuzzy duplicate lines across documents by MinHash, in DataFrame functions only.

1. Equal lines (lower-cased, trimmed) meet by a 128-bit digest alone; only distinct lines go on.
2. Signatures: every run of SHINGLE characters is hashed once and falls into one of BANDS classes, each with ROWS values: its least
   hash xor each of some masks.  Long lines use a hash-sampled part of their shingles, halved until SAMPLE to 2 * SAMPLE are left: a shingle is in every line's
   sample of a level or in none, so samples of one level estimate the same similarity.  Similar lines have sizes within
   a factor of 1 / SIMILARITY; a line whose size is so close to the next level makes a signature there too.  A line that
   repeats itself (its length then says little about the number of its shingles) also makes one of all its shingles.
3. Bands of ROWS values of two classes make buckets.  Where a bucket has two rows, sums tell whether they meet; larger ones are sorted.  Each row of a bucket carries a sketch, a few bits of each value, that estimates
   similarity without the text.  In sketch order, under which similar lines lie together whatever else is in the
   bucket, each line is held against the NEAR lines before it and the first one; so pairs are linear in rows.  A bucket
   that a hash sample shows to be large is dealt over several tasks, whose first lines meet once more.
4. Pairs whose sketches agree are verified by the exact Jaccard similarity of their shingle sets, one of each line first, then those of
   different components; components are found by star contraction.  In wide buckets that then hold several components, lines first meet a few of the largest one.  Lines that are
   still of different components all meet, in large buckets block by block; there the parity of shingle classes, a bound that
   loses no similar pair, comes before the texts.  So no pair of a bucket is left out; pairs of one component are not made.
5. The first occurrence of each component (smallest document id, then position) stays; all others go.

A pair at the similarity threshold shares a bucket with probability 0.995 or more (1 - (1 - 0.8^4)^10 if bands were independent; as classes
part a line's shingles, values vary less and short lines fare better: 0.996 to 1 in a simulation of 10 to 220 shingles, sketches included).
Its sketches agree in 42 of 48 cells on average, with a standard deviation of 3 (more if sampled).  Recall is measured against all pairs in the tests.
"""

from __future__ import annotations

import random
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, settle, staged, text_or_empty
from .components import components

SHINGLE = 5
BANDS, ROWS = 10, 4
#: Classes from a band's own one to the other one it takes values of.
SHIFT = 3
SIMILARITY = 0.8
SAMPLE = 128
#: Sketch cells, as many of two bits as fit one long and as many of four bits; and how many of them agree at least in similar lines.
FINE, COARSE, AGREE = 16, 32, 31
NEAR = 2
#: Bands whose buckets are made at a time, and the most there are: rows of all bands at once would take the most disk of all steps.
BANDS_AT_ONCE, BANDS_MOST = 4, 1000
#: Rounds in which the lines of a crowded bucket meet its largest component, and lines that stand for it in each.
ROUNDS, HUBS = 1, 4
#: Buckets of more rows are looked at for how many others each row would meet, by so many of them; from DENSE on parities, of so many
#: words (a power of two), come first.  Rows of a bucket that meet in one group.
WIDE, PROBES, DENSE, WORDS, BLOCK = 64, 8, 4, 16, 2048
#: One in HOT_SAMPLE lines tells the large buckets, those of HOT_ROWS or more; parts of a large bucket have about as many.
HOT_SAMPLE, HOT_ROWS = 64, 8192
#: Small tables go to all tasks up to this many numbers (about 30 MB); beyond it both sides are shuffled.
BROADCAST_NUMBERS = 2_000_000


def _small(df: DataFrame, extra: str | None = None) -> DataFrame:
    """df with a broadcast hint if it is a staged table of a checked size; extra is an array column that counts by its entries."""
    width = F.lit(len(df.columns)) + (F.size(extra) if extra else F.lit(0))
    return F.broadcast(df) if (df.agg(F.sum(width)).first()[0] or 0) <= BROADCAST_NUMBERS else df


def _masks(n: int) -> list[int]:
    rng = random.Random(20240229)
    return [rng.getrandbits(64) - (1 << 63) for _ in range(n)]


def _normal(line: Column) -> Column:
    return F.lower(F.trim(line))


def _lines(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc, rk, pos, line): all non-blank lines.  rk tells documents of one id apart."""
    d = docs.select(F.col(id_col).cast("long").alias("doc"), text_or_empty(F.col(text_col).cast("string")).alias("t"))
    d = d.withColumn("rk", F.xxhash64("t"))
    lines = d.select("doc", "rk", F.posexplode(F.split("t", "\n")).alias("pos", "line"))
    return lines.select("doc", "rk", "pos", _normal(F.col("line")).alias("line")).where("line <> ''")


def _first_half() -> Column:
    return F.xxhash64("line")


def _second_half() -> Column:
    return F.xxhash64(F.lit(1), F.col("line"))


def _wide(line: str) -> Column:
    """Two bytes a character, so that a shingle is a slice of bytes."""
    return F.encode(F.col(line), "UTF-16BE")


def _shingled(lines: DataFrame, shingle: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """(id, level, h): hashes of the shingles of each distinct line, at the levels it is compared at.  A line shorter than a shingle is its own single shingle."""
    distinct = lines.groupBy("id").agg(F.min("line").alias("line"))
    n = F.greatest(F.lit(1), F.char_length("line") - (shingle - 1))
    level = F.greatest(F.lit(0), F.floor(F.log2(F.col("n") / SAMPLE))).cast("int")
    close = F.col("n") >= F.pow(F.lit(2.0), F.col("level") + 1) * SAMPLE * similarity * 0.95
    seen = lambda share: F.expr(f"locate(substring(line, int(n * {share}), {shingle + 1}), line) < int(n * {share})")
    made = distinct.withColumn("n", n).withColumn("level", level).withColumn("also", F.when(close, F.col("level") + 1))
    made = made.withColumn("whole", F.when((F.col("level") > 0) & seen(0.5) & seen(0.75), 0))
    at = made.select("id", _wide("line").alias("b"), F.explode(F.array_compact(F.array("level", "also", "whole"))).alias("level"))
    rows = at.select("id", "level", "b", F.explode(F.sequence(F.lit(1), F.greatest(F.lit(1), F.length("b") - 2 * shingle + 2), F.lit(2))).alias("i"))
    rows = rows.select("id", "level", F.expr(f"xxhash64(substring(b, i, {2 * shingle}))").alias("h"))
    return rows.where("shiftrightunsigned(h, 1) <= shiftright(9223372036854775807L, level)")


def signatures(lines: DataFrame, shingle: int = SHINGLE, bands: int = BANDS, rows: int = ROWS, similarity: float = SIMILARITY) -> DataFrame:
    """(id, sketch, fine, buckets) for each distinct line and level: cells of some bits of its values, and one hash a band.

    A hash tells the class of a shingle; each class has `rows` values, the least hashes xor a mask, so a shingle counts for the values
    of one class only.  A band takes the first half of the values of its own class and the others of the class SHIFT further.
    """
    shingled = _shingled(lines, shingle, similarity).withColumn("class", F.pmod(F.shiftright("h", 20), F.lit(bands)).cast("int"))
    values = shingled.groupBy("id", "level", "class").agg(*[F.min(F.col("h").bitwiseXOR(F.lit(m))).alias(f"s{j}") for j, m in enumerate(_masks(rows))])
    # The two halves of a class may stand for one shingle each: those that a band joins are of different classes.
    half = rows - rows // 2
    cells = lambda width: reduce(Column.bitwiseOR, [F.shiftleft(F.col(f"s{j}").bitwiseAND(F.lit((1 << width) - 1)), width * j) for j in range(rows)])
    placed = lambda width, first, most: F.when((F.col("class") >= first) & (F.col("class") < first + most // rows), F.expr(f"shiftleft(c{width}, (class - {first}) * {width * rows})")).otherwise(F.lit(0).cast("long"))
    parts = values.select("id", "level", "class", F.xxhash64(*[f"s{j}" for j in range(half)]).alias("front"), F.xxhash64(F.lit(1), *[f"s{j}" for j in range(half, rows)]).alias("back"), cells(2).alias("c2"), cells(4).alias("c4"))
    parts = parts.select("id", "level", "class", "front", "back", placed(2, 0, COARSE).alias("two"), placed(4, bands - FINE // rows, FINE).alias("four"))
    of = lambda c, k: F.max(F.when(F.col("class") == k, F.col(c))).alias(f"{c}{k}")
    whole = parts.groupBy("id", "level").agg(F.bit_or("two").alias("sketch"), F.bit_or("four").alias("fine"), *[of(c, k) for c in ("front", "back") for k in range(bands)])
    key = lambda b: F.when(F.col(f"front{b}").isNotNull() | F.col(f"back{(b + SHIFT) % bands}").isNotNull(), F.xxhash64("level", F.lit(b), f"front{b}", f"back{(b + SHIFT) % bands}"))
    return whole.select("id", "sketch", "fine", F.array_compact(F.array(*[key(b) for b in range(bands)])).alias("buckets"))


def _alike(two: str, four: str) -> Column:
    """Whether enough cells agree, from the bits in which the sketches of two rows differ.  A cell differs if any of its bits does."""
    pairs = f"({four} | shiftrightunsigned({four}, 1))"
    differ = (f"bit_count(({two} | shiftrightunsigned({two}, 1)) & {int('01' * 32, 2)}L) + "
              f"bit_count(({pairs} | shiftrightunsigned({pairs}, 2)) & {int('0001' * 16, 2)}L)")
    return F.expr(f"{COARSE + FINE} - ({differ}) >= {AGREE}")


def _agree(other: str) -> Column:
    return _alike(f"(sketch ^ {other}_sketch)", f"(fine ^ {other}_fine)")


def _turned(cells: str) -> Column:
    """The sketch turned by some cells: lines that differ in one cell are not held apart by that cell in every order."""
    return F.expr(f"shiftleft(sketch, 2 * {cells}) | shiftrightunsigned(sketch, 64 - 2 * {cells})")


def _met(rows: DataFrame, by: list[str], near: int) -> DataFrame:
    """(id, others, bucket, sketch, fine): each row with those of the `near` rows before it and the first one of its group, in sketch
    order, whose sketches agree.  bucket is null where this holds every row against all others of its group; the other rows all stay."""
    w = Window.partitionBy(*by).orderBy(_turned("cast(bucket & 31 as int)"), "id")
    others = {f"p{k}": lambda c, k=k: F.lag(c, k).over(w) for k in range(1, near + 1)}
    others["p0"] = lambda c: F.first(c).over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    n = F.count(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    met = rows.select("id", "sketch", "fine", F.when((n >= near + 3) | (F.col("parts") > 1), F.col("bucket")).alias("crowd"),
                      *[f(c).alias(f"{p}_{c}") for p, f in others.items() for c in ("id", "sketch", "fine")])
    pick = [F.when(_agree(p) & (F.col("id") != F.col(f"{p}_id")), F.col(f"{p}_id")) for p in others]
    return met.select("id", F.array_compact(F.array(*pick)).alias("others"), F.col("crowd").alias("bucket"), "sketch", "fine").where("size(others) > 0 or bucket is not null")


def _met_of_many(rows: DataFrame, by: list[str], near: int) -> DataFrame:
    """_met without sorting the rows that are alone or two in their group, as most are: sums tell the pair and how its sketches differ."""
    # Both ways read all columns of one shuffle, so that it is written once.
    dealt = rows.where(" and ".join(f"{c} is not null" for c in by)).repartition(*by)
    groups = dealt.groupBy(*by).agg(F.count("*").alias("n"), F.min("id").alias("low"), F.max("id").alias("id"), F.bit_xor("sketch").alias("two"), F.bit_xor("fine").alias("four"), F.max("parts").alias("most"))
    pair = groups.where((F.col("n") == 2) & (F.col("most") == 1) & (F.col("low") != F.col("id")) & _alike("two", "four"))
    none = lambda c: F.lit(None).cast("long").alias(c)
    all_columns = reduce(Column.__and__, [F.col(c).isNotNull() for c in ("low", "id", "two", "four")])
    many = groups.where(((F.col("n") > 2) | (F.col("most") > 1)) & all_columns).select(*by)
    return pair.select("id", F.array("low").alias("others"), none("bucket"), none("sketch"), none("fine")).union(_met(dealt.join(many.hint("shuffle_hash"), by), by, near))


def _in_buckets(banded: DataFrame, bands: slice = slice(None)) -> DataFrame:
    at = range(BANDS_MOST)[bands]
    picked = F.col("buckets") if bands == slice(None) else F.slice("buckets", at.start + 1, len(at))
    return banded.select("id", "sketch", "fine", F.explode(picked).alias("bucket"))


def _large(banded: DataFrame) -> tuple[DataFrame | None, str]:
    """(bucket, parts) of the buckets that a hash sample shows to be large, staged, or None if there are none."""
    few = _in_buckets(banded.where(F.pmod(F.xxhash64("id"), F.lit(HOT_SAMPLE)) == 0)).groupBy("bucket").count()
    large = few.where(F.col("count") >= HOT_ROWS // HOT_SAMPLE).select("bucket", F.ceil(F.col("count") * HOT_SAMPLE / HOT_ROWS).cast("long").alias("parts"))
    large, path = staged(large, "line-large")
    return (large if large.limit(1).count() else None), path


def neighbours(banded: DataFrame, large: DataFrame | None, near: int = NEAR, bands: slice = slice(None)) -> DataFrame:
    """_met over the buckets of some bands: at most near + 1 others for each row of a bucket."""
    if large is None:
        return _met_of_many(_in_buckets(banded, bands).withColumn("parts", F.lit(1)), ["bucket"], near)
    dealt = _in_buckets(banded, bands).join(_small(large), "bucket", "left")
    dealt = dealt.withColumn("part", F.when(F.col("parts").isNotNull(), F.pmod(F.xxhash64("id", F.lit(7)), F.col("parts"))).otherwise(0))
    first = dealt.where("parts is not null").groupBy("bucket", "part").agg(F.min(F.struct("sketch", "id", "fine")).alias("m"))
    first = first.select("bucket", "m.sketch", "m.fine", "m.id", F.lit(1).alias("parts"))
    return _met_of_many(dealt.withColumn("parts", F.coalesce("parts", F.lit(1))), ["bucket", "part"], near).union(_met(first, ["bucket"], near))


def _ordered(a: str, b: str) -> list[Column]:
    return [F.greatest(a, b).alias("a"), F.least(a, b).alias("b")]


def _mixed(crowded: DataFrame, found: DataFrame) -> tuple[DataFrame, str]:
    """(bucket, id, sketch, fine, root, n): rows of the buckets that hold several components, staged."""
    rows = crowded.join(_small(found.withColumnsRenamed({"node": "id"})), "id", "left").withColumn("root", F.coalesce("root", "id"))
    rows, rows_path = staged(rows, "line-rooted")
    sizes = rows.groupBy("bucket").agg(F.count("*").alias("n"), F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high").select("bucket", "n")
    sizes, sizes_path = staged(sizes, "line-sizes")  # so that a broadcast of checked size, or a join that splits hot buckets, follows
    mixed, path = staged(rows.join(_small(sizes), "bucket"), "line-mixed")
    discard(crowded.sparkSession, rows_path, sizes_path)
    return mixed, path


def _other(rows: DataFrame) -> DataFrame:
    return rows.withColumnsRenamed({c: f"o_{c}" for c in rows.columns if c not in ("bucket", "n")})


def _with_hubs(mixed: DataFrame) -> DataFrame:
    """(a, b), a > b: lines of the buckets of more than WIDE rows with HUBS lines of the component that has most rows of their bucket, if it
    isn't theirs and their sketches agree.  Where fewer rows meet, `across` alone compares them, as it compares what is left of these."""
    hub = lambda k: F.min(F.struct(F.xxhash64("id", F.lit(k)), "id", "sketch", "fine"))
    wide = mixed.where(F.col("n") > WIDE)
    of_root = wide.groupBy("bucket", "root").agg(F.count("*").alias("rows"), F.array(*[hub(k) for k in range(HUBS)]).alias("hubs"))
    most = of_root.groupBy("bucket").agg(F.max(F.struct("rows", "root", "hubs")).alias("m")).where("m.rows > 1")
    hubs, _ = staged(most.select("bucket", F.col("m.root").alias("o_root"), F.inline(F.array_distinct("m.hubs"))).toDF("bucket", "o_root", "h", "o_id", "o_sketch", "o_fine").drop("h"), "line-hubs")
    met = wide.join(_small(hubs), "bucket").where((F.col("root") != F.col("o_root")) & _agree("o"))
    return met.select(*_ordered("id", "o_id")).distinct()


def _links() -> Column:
    return (F.col("root") != F.col("o_root")) & _agree("o")


def _dense(mixed: DataFrame) -> DataFrame:
    """(bucket): those of more than WIDE rows in which many lines would meet, told by a sample.  This decides on the way they are compared alone."""
    wide = mixed.where(F.col("n") > WIDE)
    probe = lambda k: F.min(F.struct(F.xxhash64("id", F.lit(-k)), "id", "root", "sketch", "fine"))
    probes = wide.groupBy("bucket").agg(F.array(*[probe(k) for k in range(1, PROBES + 1)]).alias("p")).select("bucket", F.inline("p")).drop("col1")
    some = wide.where(F.pmod(F.xxhash64("id", F.lit(13)), F.lit(PROBES)) == 0).join(_other(probes), "bucket")
    return some.where(_links()).groupBy("bucket").count().where(F.col("count") >= DENSE).select("bucket")  # about as many as a row would meet


def across(mixed: DataFrame, dense: DataFrame, parities: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """(a, b), a > b: all pairs of different components that share a bucket and whose sketches agree; in dense buckets without those
    whose parities, counted in _parities, tell that they are not similar.

    A bucket of more than BLOCK rows is cut into blocks, and each two of them, or a block and itself, meet in a group of their own.
    """
    once = F.col("id") > F.col("o_id")

    def met(rows: DataFrame, also: Column) -> list[DataFrame]:
        small, large = rows.where(F.col("n") <= BLOCK).drop("n"), rows.where(F.col("n") > BLOCK)
        blocks = F.ceil(F.col("n") / BLOCK).cast("int")
        large = large.withColumn("last", blocks - 1).withColumn("block", F.pmod(F.xxhash64("id", F.lit(11)), blocks).cast("int")).drop("n")
        one = large.withColumn("to", F.explode(F.sequence("block", "last"))).drop("last")
        two = _other(large.withColumn("to", F.col("block")).drop("last", "block")).withColumn("block", F.explode(F.sequence(F.lit(0), "o_to"))).withColumnRenamed("o_to", "to")
        in_blocks = one.join(two, ["bucket", "block", "to"]).where(((F.col("block") < F.col("to")) | once) & _links() & also)
        return [d.select(*_ordered("id", "o_id")) for d in (small.join(_other(small), "bucket").where(once & _links() & also), in_blocks)]

    differ = reduce(Column.__add__, [F.bit_count(F.col(f"m{w}").bitwiseXOR(F.col(f"o_m{w}"))) for w in range(WORDS)])
    near = differ * (1 + similarity) <= (1 - similarity) * (F.col("size") + F.col("o_size")) + 1e-6
    plain = met(mixed.join(_small(dense), "bucket", "left_anti"), F.lit(True))
    return reduce(DataFrame.union, plain + met(mixed.join(_small(dense), "bucket").join(_small(parities), "id"), near)).distinct()


def _parities(texts: DataFrame, shingle: int) -> DataFrame:
    """(id, size, m0, m1, ...): the number of different shingles, and for each of 64 * WORDS classes of them whether it has an odd number.

    Shingles that only one of two lines has are at least as many as classes in which they differ, so this bound loses no similar pair.
    """
    h = texts.select("id", F.explode(F.array_distinct(_shingles("line", shingle))).alias("h"))
    word = lambda w: F.bit_xor(F.expr(f"if((h & {WORDS - 1}) = {w}, shiftleft(1L, cast(shiftright(h, 8) & 63 as int)), 0L)")).alias(f"m{w}")
    return h.groupBy("id").agg(F.count("*").alias("size"), *[word(w) for w in range(WORDS)])


def _shingles(line: str, shingle: int) -> Column:
    """Hashes of all shingles.  The bytes are bound by an outer transform: read from the row, they would be copied for each shingle."""
    at = lambda b: F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(b) - 2 * shingle + 2), F.lit(2))
    return F.transform(F.array(_wide(line)), lambda b: F.transform(at(b), lambda i: F.xxhash64(F.substring(b, i, F.lit(2 * shingle))))).getItem(0)


def _verified(pairs: DataFrame, texts: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """The pairs (a, b) whose lines are similar.  Texts of lines that are in no pair are not shuffled."""
    side = lambda x: texts.join(_small(pairs.select(F.col(x).alias("id"))), "id", "left_semi").select(F.col("id").alias(x), F.col("line").alias(f"l{x}"))
    j = pairs.join(side("b"), "b").join(side("a"), "a")
    # One-row generators, so that the filter below is not pushed under them with its expressions repeated.
    j = j.select("a", "b", F.inline(F.array(F.struct(_shingles("la", shingle).alias("x"), _shingles("lb", shingle).alias("y")))))
    j = j.select("a", "b", F.inline(F.array(F.struct("x", "y", F.size(F.array_intersect("x", "y")).alias("both")))))
    # There are as many different shingles at most as places less common ones; only where that does not decide, they are counted.
    surely = F.col("both") * (1 + similarity) >= similarity * (F.size("x") + F.size("y")) + 1e-6
    return j.where(F.when(surely, True).otherwise(F.col("both") >= similarity * F.size(F.array_union("x", "y")))).select("a", "b")


def _apart(pairs: DataFrame, found: DataFrame) -> DataFrame:
    """(a, b, ra, rb): the pairs whose lines are of different components so far, and these."""
    roots = lambda x: _small(found.withColumnsRenamed({"node": x, "root": f"r{x}"}))
    j = pairs.join(roots("a"), "a", "left").join(roots("b"), "b", "left")
    return j.select("a", "b", F.coalesce("ra", "a").alias("ra"), F.coalesce("rb", "b").alias("rb")).where("ra <> rb")


def _merged(found: DataFrame, links: DataFrame) -> DataFrame:
    """found after more links: only the components that they join are contracted again."""
    joined, _ = staged(components(_apart(links, found), "ra", "rb"), "line-joined")
    moved = found.join(_small(joined.select(F.col("node").alias("root"), F.col("root").alias("top"))), "root", "left").select("node", F.coalesce("top", "root").alias("root"))
    return moved.union(joined.join(_small(found.select("node")), "node", "left_anti").select("node", "root"))


def line_components(lines: DataFrame, shingle: int = SHINGLE, bands: int = BANDS, rows: int = ROWS, similarity: float = SIMILARITY) -> DataFrame:
    """(node, node2, root, root2) of the distinct lines that have a partner: both halves of their and their root's digest.

    Inside, lines are named by the first half alone.  Where two lines share it, one stands for both, and only that one is
    named in the result, so no line goes for another's sake.
    """
    spark = lines.sparkSession
    named = lines.select(_first_half().alias("id"), "line")
    banded, banded_path = staged(signatures(named, shingle, bands, rows, similarity), "line-bands")
    settle(spark)
    large, large_path = _large(banded)
    met, met_paths = None, []
    for k in range(0, bands, BANDS_AT_ONCE):
        some, path = staged(neighbours(banded, large, bands=slice(k, min(k + BANDS_AT_ONCE, bands))), "line-met")
        met, met_paths = met.union(some) if met else some, [*met_paths, path]
        settle(spark)
    discard(spark, banded_path, large_path)
    pairs, pairs_path = staged(met.select("id", F.explode("others").alias("other")).select(*_ordered("id", "other")).distinct(), "line-pairs")
    crowded = met.where("bucket is not null").select("bucket", "id", "sketch", "fine")
    either = pairs.select(F.explode(F.array("a", "b")).alias("id")).union(crowded.select("id"))
    ids, ids_path = staged(either.distinct(), "line-candidates")
    texts, texts_path = staged(named.join(_small(ids), "id", "left_semi").groupBy("id").agg(F.min("line").alias("line")), "line-texts")
    settle(spark)
    # One pair of each line comes first; of the others, only those that are still of different components then.
    first, first_path = staged(pairs.groupBy("a").agg(F.min("b").alias("b")), "line-first")
    links, links_path = staged(_verified(first, texts, shingle, similarity), "line-links")
    settle(spark)
    found, found_path = staged(components(links, "a", "b"), "line-found")
    for k in range(ROUNDS + 1):
        mixed, mixed_path = _mixed(crowded, found)
        if k < ROUNDS:
            rest = pairs.join(_small(first), ["a", "b"], "left_anti")
            more = _with_hubs(mixed).join(pairs, ["a", "b"], "left_anti").union(_apart(rest, found).select("a", "b"))
        else:
            dense, dense_path = staged(_dense(mixed), "line-dense")
            lines_there, there_path = staged(mixed.join(_small(dense), "bucket", "left_semi").select("id").distinct(), "line-there")
            parities, parities_path = staged(_parities(texts.join(_small(lines_there), "id", "left_semi"), shingle), "line-parities")
            more = across(mixed, dense, parities, similarity).join(tried, ["a", "b"], "left_anti")
        more, more_path = staged(more, "line-across")
        also, also_path = staged(_verified(more, texts, shingle, similarity), "line-also")
        discard(spark, mixed_path)
        settle(spark)
        tried = pairs.union(more)
        if also.limit(1).count():
            found, found_path = staged(_merged(found, also), "line-found")
    halves = texts.select("id", _second_half().alias("half"))
    found = found.join(halves.withColumnsRenamed({"id": "node", "half": "node2"}), "node").join(halves.withColumnsRenamed({"id": "root", "half": "root2"}), "root")
    found, _ = staged(found.select("node", "node2", "root", "root2"), "line-roots")
    discard(spark, pairs_path, *met_paths, ids_path, texts_path, first_path, links_path, found_path, dense_path, there_path, parities_path)
    return found


def duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **settings) -> DataFrame:
    """(doc, rk, drop): per document the positions of lines that stay elsewhere."""
    lines = _lines(docs, id_col, text_col)
    found = line_components(lines, **settings)
    # A line is known by its component's root, one without partner by itself.
    own = lines.select("doc", "rk", "pos", _first_half().alias("node"), _second_half().alias("node2"))
    keyed = own.join(_small(found), ["node", "node2"], "left").select(
        "doc", "rk", "pos", F.coalesce("root", "node").alias("k1"), F.coalesce("root2", "node2").alias("k2"))
    keyed, keyed_path = staged(keyed, "line-places")
    many, many_path = staged(keyed.groupBy("k1", "k2").count().where(F.col("count") > 1).select("k1", "k2"), "line-repeated")
    repeated, repeated_path = staged(keyed.join(_small(many), ["k1", "k2"]), "line-copies")
    owners, owners_path = staged(repeated.groupBy("k1", "k2").agg(F.min(F.struct("doc", "rk", "pos")).alias("owner")), "line-owners")
    gone = repeated.join(_small(owners), ["k1", "k2"]).where(~F.struct("doc", "rk", "pos").eqNullSafe(F.col("owner")))
    drops, _ = staged(gone.groupBy("doc", "rk").agg(F.collect_set("pos").alias("drop")), "line-drops")
    discard(docs.sparkSession, keyed_path, many_path, repeated_path, owners_path)
    return drops


def deduplicate_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **settings) -> DataFrame:
    """docs with duplicate lines cut from the text, and columns n_lines and n_dropped (renamed over clashing ones).

    Blank lines always stay and are never duplicates.  Null texts stay null.  Lines of a document with a null id rank before all
    others.  Rows that repeat both id and text are one document: they come back alike.  An empty table gives no rows.
    """
    gone = _small(duplicates(docs, id_col, text_col, **settings), "drop")
    plain = [c for c in docs.columns if c not in ("n_lines", "n_dropped")]
    d = docs.select(*plain, F.xxhash64(text_or_empty(F.col(text_col).cast("string"))).alias("rk__"))
    j = d.join(gone, F.col(id_col).cast("long").eqNullSafe(gone["doc"]) & (d["rk__"] == gone["rk"]), "left")
    parts = F.split(F.col(text_col).cast("string"), "\n")
    kept = F.array_join(F.filter(parts, lambda x, i: ~F.array_contains(F.col("drop"), i)), "\n")
    text = F.when(F.col("drop").isNull(), F.col(text_col)).otherwise(kept).alias(text_col)
    return j.select(*[text if c == text_col else d[c] for c in plain], F.coalesce(F.size(parts), F.lit(0)).cast("long").alias("n_lines"),
                    F.coalesce(F.size("drop"), F.lit(0)).cast("long").alias("n_dropped"))
