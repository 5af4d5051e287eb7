"""Fuzzy line deduplication: MinHash over character shingles, in DataFrame functions only.

A document's lines are the pieces between line feeds, compared without outer blanks. A line's shingles
are its distinct runs of ``width`` UTF-16 code units (a shorter line is one shingle). Two lines are near
duplicates if the Jaccard similarity of their shingle sets is at least ``threshold``; near-duplicate lines form
components, and of each component only the first occurrence (smallest doc_id, then position) stays.

How it is computed
1. every line occurrence is exploded into the shingles that sign it inside one generated stage; an aggregation by line key takes
   minima of differently mixed shingle hashes, merging equal lines on the map side;
2. lines that agree in all minima of one band meet in a bucket. A bucket proposes for each member its most frequent line (near
   copies are edits of a frequent original). No bucket is capped; a hot one is shared by several tasks;
3. candidates whose sketches are close (``_APART``) are verified exactly on the texts first; verified pairs are contracted into
   components, distributed;
4. in a bucket that then holds more than one component all pairs of different components are looked at. Those that a bound on their
   shingles can't rule out are verified as well, and the components contracted again. So no pair of a bucket is lost;
5. all but the first occurrence of each component is dropped, the documents are put together again.

Lines, components and documents that hold a large share of all occurrences are joined by broadcast of at most 2000 rows (``skew``).

Defined cases: NULL text has no lines and stays NULL; blank lines always stay; rows that share doc_id and text
count as one document (all of them keep the same lines); a NULL doc_id counts as the largest; an empty table
gives an empty table; other columns pass through unchanged. A text of which all lines go becomes empty.
"""

from __future__ import annotations

import random
from functools import reduce

from pyspark.sql import Column, DataFrame, Window, functions as F

from graphdist.llm.skew import SHARE, spread_join
from graphdist.operators.components import connected_components
from graphdist.runtime import discard, materialize

WIDTH, THRESHOLD, BANDS, ROWS = 8, 0.8, 7, 3
_WORDS, _SAMPLE, _SPLIT = 8, 64, 4096
#: A sketch holds two bits of 32 minima; a pair whose sketches differ in more than 11 is not verified first, only if its components
#: still differ then. At the threshold 4.4 of the 29 minima outside the common band are expected to differ (deviation 1.9).
_SKETCH, _APART = 32, 11
#: Words of 64 bits of the set that holds a line's shingle hashes (a power of two).
_WORDS_OF_BITS = 32
_LAST = 2**63 - 1


def _factors(n: int) -> list[int]:
    """Odd numbers of 31 bits: the middle bits of a product with one are a hash of the other factor."""
    r = random.Random(20)
    return [r.getrandbits(31) | (1 << 30) | 1 for _ in range(n)]


def _occurrences(docs: DataFrame) -> DataFrame:
    """(d, th, pos, line, id, alt): every non-blank line; id and alt are independent 64-bit hashes of it."""
    lines = docs.select(
        F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("d"),
        F.xxhash64("text").alias("th"),
        F.posexplode(F.split("text", "\n")).alias("pos", "line"),
    ).select("d", "th", "pos", F.trim("line").alias("line"))
    return lines.filter("line != ''").select("d", "th", "pos", "line", F.xxhash64("line").alias("id"), F.xxhash64(F.lit(1), "line").alias("alt"))


def _units(line: Column) -> Column:
    return F.encode(line, "UTF-16BE")


def _signatures(occ: DataFrame, width: int, bands: int, rows: int) -> DataFrame:
    """(id, alt, n, sketch, keys): signatures of every distinct line with its number of occurrences.

    A line of many words is signed by its shingles that begin with a blank (and its first one), any other line by all its
    shingles. Near duplicates have about as many blanks and units, and a line near the border gets a signature of either kind, so two
    of them share a kind.
    ``sketch`` holds two bits of each minimum; a key is a band's bucket and another band's minimum.
    """
    n_minima = bands * rows
    length = F.octet_length("line")
    blanks = length - F.octet_length(F.replace("line", F.lit(" ")))
    by_words = (blanks >= _WORDS) & (blanks * 16 >= length)
    by_units = (blanks < _WORDS * 5 / 4) | (blanks * 10 < length)
    n = F.greatest(F.lit(0), (F.length("u") / 2).cast("int") - width) + 1
    lines = occ.select("id", "alt", _units(F.col("line")).alias("u"), by_words.alias("w"), by_units.alias("s")).withColumn("n", n)
    # places 0 .. n - 1 are those of the first kind, n .. 2 * n - 1 those of the second: one generator for both
    places = F.explode(F.sequence(F.when(F.col("w"), 0).otherwise(F.col("n")), F.when(F.col("s"), 2 * F.col("n")).otherwise(F.col("n")) - 1))
    placed = lines.select("id", "alt", "u", "n", places.alias("p"))
    signing = placed.filter((F.col("p") >= F.col("n")) | (F.col("p") == 0) | (F.substring("u", F.col("p") * 2 + 1, 2) == F.lit(b"\x00 ")))
    at = F.when(F.col("p") >= F.col("n"), F.col("p") - F.col("n")).otherwise(F.col("p"))
    h = F.hash(F.substring("u", at * 2 + 1, 2 * width)).bitwiseAND(F.lit(0x7FFFFFFF)).cast("long")
    first = ((F.col("p") == 0) | (F.col("p") == F.col("n"))).cast("int")
    hashed = signing.select("id", "alt", (F.col("p") < F.col("n")).alias("k"), first.alias("first"), h.alias("h"))
    mixed = lambda f: F.shiftright(F.col("h") * F.lit(f).cast("long"), 15).bitwiseAND(F.lit(0x7FFFFFFF).cast("long")).cast("int")
    minima = [F.min(mixed(f)).alias(f"m{k}") for k, f in enumerate(_factors(max(n_minima, _SKETCH)))]
    signed = hashed.groupBy("id", "k").agg(*minima, F.min("alt").alias("alt"), F.sum("first").alias("n"))
    sketch = reduce(Column.bitwiseOR, [F.shiftleft(F.col(f"m{k}").bitwiseAND(F.lit(3)).cast("long"), 2 * k) for k in range(_SKETCH)])
    keys = F.array(
        *[
            F.struct(F.xxhash64(F.lit(b), "k", *[f"m{b * rows + r}" for r in range(rows)]).alias("bucket"), F.col(f"m{(b + 1) % bands * rows}").alias("tie"))
            for b in range(bands)
        ]
    )
    return signed.select("id", "alt", "n", sketch.alias("sketch"), keys.alias("keys"))


def _hot_buckets(signed: DataFrame, bands: int) -> DataFrame:
    """(bucket, salts): buckets that hold at least one in ``SHARE`` of the lines, by a sample of the lines.

    At most ``bands * SHARE`` rows. It only decides how a bucket is shared by tasks, not what is compared.
    """
    sample = signed.filter(F.pmod(F.xxhash64("id"), F.lit(_SAMPLE)) == 0)
    least = max(_SPLIT // _SAMPLE, signed.count() // _SAMPLE // SHARE)
    counted = sample.select(F.explode("keys").alias("k")).groupBy("k.bucket").count().filter(F.col("count") >= least)
    return counted.select("bucket", F.ceil(F.col("count") * _SAMPLE / _SPLIT).cast("int").alias("salts"))


def _meetings(signed: DataFrame, bands: int) -> DataFrame:
    """(bucket, part, id, sketch, head, head_sketch): each member of a bucket of several lines.

    The head is the most frequent line. A hot bucket is dealt to parts, each with a head of its own; these heads meet once more
    (part -1).
    """
    placed = signed.select("id", "n", "sketch", F.explode("keys").alias("k")).select("k.bucket", "k.tie", "id", "n", "sketch")
    placed = placed.join(F.broadcast(_hot_buckets(signed, bands)), "bucket", "left")
    placed = placed.withColumn("part", F.when(F.col("salts").isNull(), 0).otherwise(F.pmod(F.xxhash64("id"), F.col("salts")) + 1).cast("int"))

    def meet(rows, *key):
        w = Window.partitionBy(*key).orderBy(F.desc("n"), "tie", "id")
        first = w.rowsBetween(Window.unboundedPreceding, 0)
        found = rows.select(
            "bucket", "part", "id", "n", "tie", "sketch", F.first("id").over(first).alias("head"), F.first("sketch").over(first).alias("head_sketch"),
            F.row_number().over(w).alias("place"), F.lead("id").over(w).alias("one"),
        )
        return found.filter("place > 1 or one is not null or part > 0").drop("place", "one")

    met = materialize(meet(placed, "bucket", "part"), "line-meetings")
    tops = meet(met.filter("part > 0 and id = head").withColumn("part", F.lit(-1)), "bucket")
    both = materialize(met.union(tops).drop("n", "tie"), "line-meetings")
    discard(met)
    return both


def _differ(a: str, b: str) -> Column:
    """How many of the sketch's minima differ in their two bits (at the threshold 0.8 three in twenty are expected to)."""
    x = F.col(a).bitwiseXOR(F.col(b))
    return F.bit_count(x.bitwiseOR(F.shiftrightunsigned(x, 1)).bitwiseAND(F.lit(0x5555555555555555)))


def _ordered(rows: DataFrame, x: str, y: str) -> DataFrame:
    return rows.select(F.least(x, y).alias("x"), F.greatest(x, y).alias("y")).distinct()


def _proposed(met: DataFrame) -> DataFrame:
    """(x, y): each member with the head of its bucket, if their sketches allow."""
    return _ordered(met.filter((F.col("id") != F.col("head")) & (_differ("sketch", "head_sketch") <= _APART)), "id", "head")


def _candidates(occ: DataFrame, width: int, bands: int, rows: int) -> DataFrame:
    return _proposed(_meetings(_signatures(occ, width, bands, rows), bands))


def _crossing(met: DataFrame, comp: DataFrame) -> DataFrame:
    """(bucket, part, id, c, main): members of the buckets that hold more than one component; ``main`` is a bucket's largest."""
    rows = met.filter("part >= 0").select("bucket", "part", "id").join(comp.withColumnRenamed("component", "c"), "id", "left")
    rows = rows.withColumn("c", F.coalesce("c", "id"))
    sizes = rows.groupBy("bucket", "c").agg(F.count("*").alias("n"))
    split = sizes.groupBy("bucket").agg(F.count("*").alias("k"), F.max_by("c", F.struct("n", "c")).alias("main")).filter("k > 1")
    return materialize(rows.join(split.select("bucket", "main").hint("shuffle_hash"), "bucket").select("bucket", "part", "id", "c", "main"), "line-crossing")


def _profiles(texts: DataFrame, width: int) -> DataFrame:
    """(id, n, p, b0 ..): a set of ``64 * _WORDS_OF_BITS`` bits that holds the hashes of a line's shingles; a line has at most n and at
    least p distinct ones.

    A bit that only one of two lines has stands for at least one shingle that only this line has. A shingle meets one word of its line
    (id, k); the words are put side by side afterwards, so a shingle costs one update and not one a word.
    """
    n = F.greatest(F.lit(0), (F.length("u") / 2).cast("int") - width) + 1
    placed = texts.select("id", "u", n.alias("n")).select("id", "u", "n", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("at"))
    hashed = placed.select("id", "n", F.hash(F.substring("u", F.col("at") * 2 + 1, 2 * width)).alias("h"))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("h").bitwiseAND(F.lit(63)))
    word = F.shiftright("h", 6).bitwiseAND(F.lit(_WORDS_OF_BITS - 1)).alias("k")
    words = hashed.select("id", "n", word, bit.alias("bit")).groupBy("id", "k").agg(F.max("n").alias("n"), F.bit_or("bit").alias("word"))
    aside = [F.max(F.when(F.col("k") == k, F.col("word"))).alias(f"b{k}") for k in range(_WORDS_OF_BITS)]
    rows = words.groupBy("id").agg(F.max("n").alias("n"), F.sum(F.bit_count("word")).cast("int").alias("p"), *aside)
    return rows.select("id", "n", "p", *[F.coalesce(f"b{k}", F.lit(0).cast("long")).alias(f"b{k}") for k in range(_WORDS_OF_BITS)])


def _remainder(crossing: DataFrame, texts: DataFrame, pairs: DataFrame, threshold: float, width: int) -> DataFrame:
    """(x, y): all pairs of different components that share a bucket and may reach the threshold.

    Every pair of a bucket is looked at, except pairs within its largest component. Lines at the threshold differ in at most
    ``(1 - threshold) / (1 + threshold)`` of their shingles, and in no more bits; a pair with more differing bits is left out. The
    parts of a hot bucket meet each other in different tasks.
    """
    ids = crossing.select("id").distinct()
    profiles = _profiles(texts.join(ids.hint("shuffle_hash"), "id", "left_semi"), width)
    full = materialize(crossing.join(profiles, "id"), "line-profiles")
    other = full.drop("main").select("bucket", "part", *[F.col(c).alias(f"o_{c}") for c in full.columns if c not in ("bucket", "part", "main")])
    hot = crossing.filter("part > 0").select("bucket", "part").distinct()
    other = other.filter("part = 0").unionByName(other.filter("part > 0").drop("part").join(F.broadcast(hot), "bucket"))
    differ = reduce(Column.__add__, [F.bit_count(F.col(f"b{k}").bitwiseXOR(F.col(f"o_b{k}"))) for k in range(_WORDS_OF_BITS)])
    once = (F.col("c") != F.col("o_c")) & ((F.col("o_c") == F.col("main")) | (F.col("id") < F.col("o_id")))
    most = (F.col("n") + F.col("o_n")) * F.lit((1 - threshold) / (1 + threshold)) + F.lit(1e-6)
    sizes = (F.col("n") >= F.col("o_p") * F.lit(threshold) - F.lit(1e-6)) & (F.col("o_n") >= F.col("p") * F.lit(threshold) - F.lit(1e-6))
    met = full.filter("c != main").join(other.hint("shuffle_hash"), ["bucket", "part"]).filter(once & sizes & (differ <= most))
    found = materialize(_ordered(met.select("id", "o_id"), "id", "o_id").join(pairs, ["x", "y"], "left_anti"), "line-pairs")
    discard(full)
    return found


def _shingles(u: str, width: int) -> Column:
    """Hashes of the distinct shingles. The outer ``transform`` hands the bytes over once, not once a shingle."""
    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(u) - 2 * width + 1), F.lit(2))
    cut = F.transform(F.array(F.col(u)), lambda v: F.transform(starts, lambda i: F.xxhash64(F.substring(v, i, F.lit(2 * width)))))
    return F.array_distinct(F.flatten(cut))


def _similarity(pairs: DataFrame, texts: DataFrame, width: int) -> DataFrame:
    """(x, y, j): exact Jaccard similarity of the shingle sets of the lines x and y."""
    left = texts.select(F.col("id").alias("x"), F.col("u").alias("ux"))
    right = texts.select(F.col("id").alias("y"), F.col("u").alias("uy"))
    met = pairs.join(left, "x").join(right, "y").select("x", "y", _shingles("ux", width).alias("sx"), _shingles("uy", width).alias("sy"))
    counted = met.select("x", "y", F.size("sx").alias("nx"), F.size("sy").alias("ny"), F.size(F.array_intersect("sx", "sy")).alias("n"))
    return counted.select("x", "y", (F.col("n") / (F.col("nx") + F.col("ny") - F.col("n"))).alias("j"))


def _texts(occ: DataFrame, wanted: DataFrame) -> DataFrame:
    """(id, u): the code units of the wanted lines; a task sends one row a line, however often it occurs."""
    lines = occ.select("id", "line").groupBy("id").agg(F.first("line").alias("line"))
    return lines.join(wanted.hint("shuffle_hash"), "id", "left_semi").select("id", _units(F.col("line")).alias("u"))


def _components(occ: DataFrame, signed: DataFrame, threshold: float, width: int, bands: int, rows: int) -> DataFrame:
    met = _meetings(signed, bands)
    pairs = materialize(_proposed(met), "line-pairs")
    wanted = met.select("id").distinct()
    texts = materialize(_texts(occ, wanted), "line-texts")
    near = lambda some: _similarity(some, texts, width).filter(F.col("j") >= threshold).select(F.col("x").alias("a"), F.col("y").alias("b"))
    links = materialize(near(pairs), "line-links")
    comp = connected_components(links)
    crossing = _crossing(met, comp)
    discard(met)
    rest = _remainder(crossing, texts, pairs, threshold, width)
    discard(crossing, pairs)
    more = materialize(near(rest), "line-links")
    discard(rest, texts)
    if not more.isEmpty():
        comp = connected_components(comp.select(F.col("id").alias("a"), F.col("component").alias("b")).union(more))
    discard(more, links)
    return comp


def line_components(docs: DataFrame, threshold: float = THRESHOLD, width: int = WIDTH, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(id, component): every line that has a near duplicate with another text."""
    occ = _occurrences(docs)
    signed = materialize(_signatures(occ, width, bands, rows), "line-signatures")
    comp = _components(occ, signed, threshold, width, bands, rows)
    discard(signed)
    return comp


def repeated_lines(docs: DataFrame, threshold: float = THRESHOLD, width: int = WIDTH, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(d, th, gone, n): positions of the lines that go, for each document that loses any; n lines in all its rows."""
    occ = _occurrences(docs)
    signed = materialize(_signatures(occ, width, bands, rows), "line-signatures")
    comp = _components(occ, signed, threshold, width, bands, rows)
    lines = signed.select("id", "alt", "n").dropDuplicates(["id"])
    lines = lines.join(comp.hint("shuffle_hash"), "id", "left").filter("n > 1 or component is not null")
    classes = materialize(lines.select("id", "alt", "n", F.coalesce("component", "id").alias("c")), "line-classes")
    discard(signed)
    total = classes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    within = spread_join(occ.select("d", "th", "pos", "id", "alt"), classes, ["id", "alt"], "n", total).filter("c is not null").select("c", "d", "th", "pos")
    within = materialize(within, "line-classes")
    firsts = within.groupBy("c").agg(F.min(F.struct("d", "th", "pos")).alias("f"), F.count("*").alias("n"))
    later = spread_join(within, firsts, ["c"], "n", total).filter(F.struct("d", "th", "pos") > F.col("f"))
    gone = materialize(later.groupBy("d", "th").agg(F.collect_set("pos").alias("gone"), F.count("*").alias("n")), "line-gone")
    discard(classes, within)
    return gone


def dedup_lines(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with the lines that go removed from ``text``; further columns n_lines and n_removed."""
    names = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    gone = repeated_lines(docs, **options)
    packed = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"),
        F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("d"),
        F.xxhash64("text").alias("th"),
    )
    left = lambda v: F.array_except(F.sequence(F.lit(0), F.size(v) - 1), F.col("gone"))
    # the outer transform splits a text once, not once a line
    kept = F.get(F.transform(F.array(F.split("row.text", "\n")), lambda v: F.array_join(F.transform(left(v), lambda i: F.get(v, i)), "\n")), F.lit(0))
    total = gone.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    joined = spread_join(packed, gone, ["d", "th"], "n", total)  # the side of the lines that go is small, the texts aren't sorted
    text = F.when(F.col("gone").isNull(), F.col("row.text")).otherwise(kept)
    n_lines = F.octet_length("row.text") - F.octet_length(F.replace("row.text", F.lit("\n"))) + 1
    return joined.select(
        *[text.alias("text") if c == "text" else F.col(f"row.`{c}`").alias(c) for c in names],
        F.when(F.col("row.text").isNull(), 0).otherwise(n_lines).alias("n_lines"),
        F.coalesce(F.size("gone"), F.lit(0)).alias("n_removed"),
    )


def op1_line_dedup(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return dedup_lines(docs).select(
        "doc_id", F.col("n_lines").cast("long").alias("n_lines"), F.col("n_removed").cast("long").alias("n_removed"), "text"
    )
