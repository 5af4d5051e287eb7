"""SimHash near-duplicate detection by a segment-popcount embedding.

Fingerprint: A-Z lower-cased, words ``[^\\x20\\x09-\\x0D]+``, shingles of 4 words with repeats, XXH64 with seed 42;
a bit is set if more than half of the hashes have it. Documents link at ``distance`` or fewer differing bits.

Search: a fingerprint is cut into 32 segments of two bits and embedded as its vector of segment bit counts. The
Manhattan distance of two such vectors never exceeds the Hamming distance of the fingerprints. The 32 coordinates
are dealt to ``distance + 2`` groups; if the Manhattan distance is at most ``distance``, at least two groups agree
exactly, so every link falls into a grid cell named by a pair of groups and their counts. Inside a cell, a range
join over the total bit count (it differs by at most ``distance``) feeds the exact Hamming test.

Equal fingerprints are merged first. A crowded cell is cut into blocks and its pairs of blocks are dealt to
different tasks, so no task holds a whole group. A task returns a spanning forest of the links it finds instead of
all pairs, which keeps the components exact. Components come from distributed star contraction.

Defined cases: NULL or blank text has fingerprint zero, linked like any other; repeated rows get the same
component; a NULL doc_id keeps its row, gets a component by its links but never names one unless alone
(then NULL); an empty table gives an empty table; other columns are dropped by ``near_duplicate_groups`` and stay in ``keep_one_per_group``.
"""

from __future__ import annotations

from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from graphdist.llm.arrow_io import column_bytes, slices, tidy
from graphdist.llm.skew import spread_join
from graphdist.operators.components import connected_components
from graphdist.runtime import materialize

SHINGLE, DISTANCE, BLOCK, SLICE = 4, 4, 2048, 8 << 20
_LOWER = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
_LOW_BITS = 0x5555555555555555


def fingerprint(text: bytes | None, size: int = SHINGLE) -> int:
    words = (text or b"").translate(_LOWER).split()
    if not words:
        return 0
    joined = b" ".join(words)
    starts = [0, *accumulate(len(w) + 1 for w in words)]
    digest = xxhash.xxh64_intdigest
    if len(words) < size:
        hashes = np.array([digest(joined, 42)], dtype="<u8")
    else:
        hashes = np.array([digest(joined[a : b - 1], 42) for a, b in zip(starts, starts[size:])], dtype="<u8")
    ones = np.zeros(64, dtype=np.int64)
    for k in range(0, len(hashes), 1 << 14):
        part = hashes[k : k + (1 << 14)]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = np.packbits(2 * ones > len(hashes), bitorder="little")
    return int(bits.view("<u8")[0])


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def fingerprints(docs: DataFrame, text: str = "text", size: int = SHINGLE) -> DataFrame:
    """(doc_id, th, fp) with fp the 64 bits as a signed long and th a hash of the text."""

    @tidy
    def run(batches):
        for whole in batches:
            for b in slices(whole, "text", SLICE):
                fps = [_signed(fingerprint(t, size)) for t in column_bytes(b, "text")]
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fps, pa.int64())], ["doc_id", "th", "fp"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.col(text)).alias("th"), F.col(text).alias("text"))
    return rows.mapInArrow(run, "doc_id long, th long, fp long")


def _counts(fp):
    """Bit counts of the 32 two-bit segments, each still at its place in the word."""
    low = fp.bitwiseAND(F.lit(_LOW_BITS))
    high = F.shiftrightunsigned(fp, 1).bitwiseAND(F.lit(_LOW_BITS))
    both = low.bitwiseAND(high)  # a segment with two bits: 2 = binary 10
    one = low.bitwiseXOR(high)
    return one.bitwiseOR(F.shiftleft(both, 1))


def _groups(n: int) -> list[int]:
    """Masks of n groups of neighbouring segments."""
    edges = [round(k * 32 / n) for k in range(n + 1)]
    out = []
    for a, b in zip(edges, edges[1:]):
        m = sum(3 << (2 * s) for s in range(a, b))
        out.append(_signed(m))
    return out


def _forest(fps: np.ndarray, other: np.ndarray | None, distance: int) -> list[tuple[int, int]]:
    """A spanning forest of the links inside ``fps``, or between ``fps`` and ``other``."""
    both = fps if other is None else np.concatenate([fps, other])
    ones = np.bitwise_count(both).astype(np.int64)
    order = np.argsort(ones, kind="stable")
    values, ones = both[order], ones[order]
    side = None if other is None else (order >= len(fps))
    parent = list(range(len(values)))

    def root(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    ends = np.searchsorted(ones, ones + distance, side="right")
    for i in range(len(values) - 1):
        near = values[i + 1 : ends[i]]
        if not len(near):
            continue
        hit = np.bitwise_count(near ^ values[i]) <= distance
        if side is not None:
            hit &= side[i + 1 : ends[i]] != side[i]
        for j in np.flatnonzero(hit):
            a, b = root(i), root(i + 1 + int(j))
            if a != b:
                parent[b] = a
                out.append((int(values[i].view(np.int64)), int(values[i + 1 + int(j)].view(np.int64))))
    return out


def _links_of_sorted(distance: int):
    """Links from rows sorted by (cell, part, fp); rows of one cell and part are one group."""

    def group(rows):
        fps = np.array([r[0] for r in rows], dtype=np.int64).view(np.uint64)
        sides = np.array([r[1] for r in rows])
        if (sides == 0).all():
            return _forest(fps, None, distance)
        return _forest(fps[sides == 1], fps[sides == 2], distance)

    @tidy
    def run(batches):
        key, held = None, []
        for b in batches:
            cells = b.column(0).to_numpy(zero_copy_only=False)
            parts = b.column(1).to_numpy(zero_copy_only=False)
            fps = b.column(2).to_numpy(zero_copy_only=False)
            sides = b.column(3).to_numpy(zero_copy_only=False)
            new = np.flatnonzero(np.r_[True, (cells[1:] != cells[:-1]) | (parts[1:] != parts[:-1])])
            out = []
            bounds = [*new.tolist(), len(cells)]
            for a, e in zip(bounds, bounds[1:]):
                k = (cells[a], parts[a])
                if k != key:
                    if len(held) > 1:
                        out += group(held)
                    key, held = k, []
                if e - a == 1:
                    held.append((fps[a], sides[a]))
                else:
                    held.extend(zip(fps[a:e], sides[a:e]))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in out], pa.int64()), pa.array([y for _, y in out], pa.int64())], ["a", "b"])
        if len(held) > 1 and (out := group(held)):
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in out], pa.int64()), pa.array([y for _, y in out], pa.int64())], ["a", "b"])

    return run


def links(fps: DataFrame, distance: int = DISTANCE, block: int = BLOCK) -> DataFrame:
    """(a, b): links between different fingerprints that connect everything all links would."""
    masks = _groups(distance + 2)
    v = _counts(F.col("fp"))
    cells = F.array(*[F.xxhash64(F.lit(k), v.bitwiseAND(F.lit(x)), v.bitwiseAND(F.lit(y))) for k, (x, y) in enumerate(combinations(masks, 2))])
    placed = fps.select("fp").distinct().select("fp", F.explode(cells).alias("cell"))
    crowded = placed.groupBy("cell").count().filter(F.col("count") > block).select("cell", F.ceil(F.col("count") / block).cast("int").alias("n"))
    dealt = placed.join(crowded, "cell", "left").withColumn("mine", F.when(F.col("n").isNotNull(), F.pmod(F.xxhash64(F.lit(3), "fp"), F.col("n")).cast("int")))
    # in a crowded cell a block meets itself and every other block: part = (smaller block, larger block)
    parts = F.when(F.col("n").isNull(), F.array(F.struct(F.lit(0).cast("long").alias("part"), F.lit(0).alias("side")))).otherwise(
        F.transform(
            F.sequence(F.lit(0), F.col("n") - 1),
            lambda o: F.struct(
                (F.least(o, F.col("mine")).cast("long") * F.col("n") + F.greatest(o, F.col("mine")) + 1).alias("part"),
                F.when(o == F.col("mine"), 0).when(F.col("mine") < o, 1).otherwise(2).alias("side"),
            ),
        )
    )
    spread = dealt.select("cell", "fp", F.explode(parts).alias("p")).select("cell", F.col("p.part").alias("part"), "fp", F.col("p.side").alias("side"))
    n = int(fps.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    grid = spread.repartition(n, "cell", "part").sortWithinPartitions("cell", "part", "fp")
    return grid.mapInArrow(_links_of_sorted(distance), "a long, b long").distinct()


def _grouped(docs: DataFrame, distance: int, size: int, text: str) -> DataFrame:
    """(doc_id, th, fp, c, component_id): c names the component by a fingerprint. Groups that hold many rows are joined by broadcast."""
    found = materialize(fingerprints(docs, text, size), "simhash")
    comp = connected_components(links(found.select("fp"), distance))
    each = found.groupBy("fp").agg(F.count("*").alias("n"), F.min("doc_id").alias("least"))
    each = materialize(each.join(comp.withColumnRenamed("id", "fp"), "fp", "left").select("fp", "n", "least", F.coalesce("component", "fp").alias("c")), "simhash")
    smallest = each.groupBy("c").agg(F.min("least").alias("component_id"), F.count("*").alias("w"))
    named = spread_join(each.select("fp", "n", "c"), smallest, ["c"], "w", each.count())
    return spread_join(found, named, ["fp"], "n", found.count())


def near_duplicate_groups(docs: DataFrame, distance: int = DISTANCE, size: int = SHINGLE, text: str = "text") -> DataFrame:
    """(doc_id, fp, component_id): one row per document; component_id is the smallest doc_id reachable."""
    return _grouped(docs, distance, size, text).select("doc_id", "fp", "component_id")


def keep_one_per_group(docs: DataFrame, distance: int = DISTANCE, size: int = SHINGLE, text: str = "text") -> DataFrame:
    """The documents that stay: of each component the one with the smallest doc_id.

    Rows that repeat this doc_id within the component leave the one whose text has the smallest hash; rows without a doc_id all stay.
    """
    found = _grouped(docs, distance, size, text).filter("doc_id = component_id")
    stays = found.groupBy("doc_id", "c").agg(F.min("th").alias("_th")).select(F.col("doc_id").alias("_id"), "_th").distinct()
    row = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").cast("long").alias("_id"), F.xxhash64(F.col(text)).alias("_th"))
    kept = row.join(stays, ["_id", "_th"], "left_semi").dropDuplicates(["_id", "_th"]).unionByName(row.filter("_id is null"))
    return kept.select(*[F.col(f"row.`{c}`").alias(c) for c in docs.columns])


def op5_simhash_dedup(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = near_duplicate_groups(docs)
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
