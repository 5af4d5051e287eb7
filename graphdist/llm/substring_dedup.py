"""Substring deduplication over windows of 13 words, by super-k-mer partitioning.

Words ``[^\\x20\\x09-\\x0D]+`` stay unchanged. A word is removed if a window over it has a word sequence that also
starts in a document with a smaller doc_id (judged on the input).

1. A task slides over each document: the minimiser of a window is its smallest word, in an order of hashes in which
   the words that a sample found often come late, by the binary size of their counts, and words of up to 3 bytes last (frequent words would
   make hot buckets). Any order gives the same result; the sample only evens the buckets. A run of windows with one minimiser travels as one packed string (its words, once) to the bucket of that
   minimiser. Equal runs inside a batch are merged first: occurrences in other documents than the smallest are
   settled there and only their positions go on, so a passage in a third of all rows costs one string a batch.
   Strings for one bucket are packed into one compressed block.
2. There are as many buckets as the strings (``OVERLAP`` times the text) fill at about ``BUCKET`` bytes each. A bucket numbers its words, numbers its windows by sorting the rows of word numbers (exact: equal numbers mean
   equal words), and marks each window that a smaller doc_id has too.
3. Marks and texts meet by document in sorted order; a task streams through them and rewrites one text at a time.

Defined cases: NULL text has no words (its kept text is NULL); fewer than 13 words have no window; rows that share
doc_id and text get the same result and don't remove from each other; rows with a NULL doc_id neither remove nor
lose words; an empty table gives an empty table; other columns pass through.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections import defaultdict
from itertools import count

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, functions as F, types as T

from graphdist.llm.arrow_io import column_bytes, slices, tidy
from graphdist.llm.skew import spread_join
from graphdist.runtime import materialize

WINDOW, PIECE = 13, 8 << 20
#: Bytes of strings a bucket is meant to hold, and a task holds of one bucket; what goes beyond is counted by Spark.
BUCKET, HELD = 8 << 20, 24 << 20
#: Bytes of strings a byte of text: neighbouring runs share 12 words.
OVERLAP = 3
#: Text whose words are counted, and words that get a place in the order by their counts.
SAMPLE, FREQUENT = 16 << 20, 8192
_HEAD = "<qiii"  # doc_id, text hash, first window, bytes that follow


def _ranks(counts: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of frequent words, ascending, and the binary sizes of their counts."""
    counts = sorted(counts)
    return np.array([h for h, _ in counts], dtype=np.int64), np.array([n.bit_length() for _, n in counts], dtype=np.int64)


def _minimisers(words: list[bytes], sizes: np.ndarray, window: int, ranks: tuple[np.ndarray, np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """For each window the place and the value of its minimiser (leftmost of the smallest)."""
    h = np.fromiter(map(zlib.crc32, words), dtype=np.int64, count=len(words))
    if ranks is not None and len(ranks[0]):
        at = np.minimum(np.searchsorted(ranks[0], h), len(ranks[0]) - 1)
        h |= np.where(ranks[0][at] == h, ranks[1][at], 0) << 32
    h |= (sizes <= 3).astype(np.int64) << 40
    at = np.lib.stride_tricks.sliding_window_view(h, window).argmin(axis=1)
    place = at + np.arange(len(at))
    return place, h[place]


def _runs(text: bytes, window: int, ranks=None):
    """(first window, number of windows, minimiser value, packed words) for each run."""
    words = text.split()
    if len(words) < window:
        return
    sizes = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    place, value = _minimisers(words, sizes, window, ranks)
    joined = b" ".join(words)
    ends = np.cumsum(sizes + 1)
    starts = np.concatenate([[0], ends[:-1]])
    first = np.flatnonzero(np.r_[True, place[1:] != place[:-1]])
    count = np.diff(np.r_[first, len(place)])
    lo = starts[first].tolist()
    hi = (ends[first + count + window - 2] - 1).tolist()
    for f, c, v, a, b in zip(first.tolist(), count.tolist(), value[first].tolist(), lo, hi):
        yield f, c, v, joined[a:b]


def _pack_marks(marks: list[tuple[int, int]]) -> bytes:
    return np.array(marks, dtype="<i4").tobytes()


def _scatter(buckets: int, window: int, ranks=None):
    """Documents -> (bucket, blob): super-k-mers, and settled marks on their way to any bucket."""

    @tidy
    def run(batches):
        packer = zstandard.ZstdCompressor(level=3)
        for whole in batches:
            for b in slices(whole, "text", PIECE):
                seen: dict = {}
                settled: dict = {}
                for doc, th, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), column_bytes(b, "text")):
                    if doc is None or text is None:
                        continue
                    for f, c, v, s in _runs(text, window, ranks):
                        old = seen.get(s)
                        if old is None:
                            seen[s] = [v, doc, [(th, f, c)]]
                        elif old[1] == doc:
                            old[2].append((th, f, c))
                        elif old[1] < doc:
                            settled.setdefault((doc, th), []).append((f, c))
                        else:
                            for t, of, oc in old[2]:
                                settled.setdefault((old[1], t), []).append((of, oc))
                            old[1], old[2] = doc, [(th, f, c)]
                out: dict[int, list[bytes]] = {}
                for s, (v, doc, places) in seen.items():
                    parts = out.setdefault(v % buckets, [])
                    for th, f, c in dict.fromkeys(places):
                        parts.append(struct.pack(_HEAD, doc, th, f, len(s)))
                        parts.append(s)
                keys, blobs = [], []
                for k, parts in out.items():
                    keys.append(k)
                    blobs.append(b"K" + packer.compress(b"".join(parts)))
                for (doc, th), marks in settled.items():
                    parts = out.setdefault(-1 - doc % buckets, [])
                    parts.append(struct.pack(_HEAD, doc, th, 0, 8 * len(marks)))
                    parts.append(_pack_marks(marks))
                for k in [k for k in out if k < 0]:
                    keys.append(-1 - k)
                    blobs.append(b"M" + packer.compress(b"".join(out[k])))
                if keys:
                    yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int32()), pa.array(blobs, pa.binary())], ["bucket", "blob"])

    return run


def _records(blob: bytes, unpack):
    data = unpack.decompress(blob[1:])
    at = 0
    while at < len(data):
        doc, th, f, n = struct.unpack_from(_HEAD, data, at)
        at += 20
        yield doc, th, f, data[at : at + n]
        at += n


def _duplicate_windows(records: list, window: int) -> dict:
    """Marks (first, count) by (doc, th): windows of a bucket that a smaller doc_id has as well."""
    docs, ths, firsts, strings = zip(*records)
    words = b" ".join(strings).split()
    size = np.array([s.count(b" ") + 1 for s in strings], dtype=np.int64)
    number: dict[bytes, int] = defaultdict(count().__next__)
    code = np.fromiter(map(number.__getitem__, words), dtype=np.int32, count=len(words))
    del words
    counts = size - window + 1
    total = int(counts.sum())
    base = np.cumsum(size) - size
    of = np.repeat(np.arange(len(size)), counts)
    inner = np.arange(total) - np.repeat(np.cumsum(counts) - counts, counts)
    start = base[of] + inner
    mix = np.zeros(total, dtype=np.uint64)
    spread = np.random.default_rng(5).integers(1, 2**63, size=window, dtype=np.uint64) | np.uint64(1)
    for k in range(window):
        t = (code[start + k].astype(np.uint64) + np.uint64(1)) * spread[k]
        mix += t ^ (t >> np.uint64(31))
    doc = np.array(docs, dtype=np.int64)[of]
    order = np.lexsort((doc, mix))
    m, d, st = mix[order], doc[order], start[order]
    same = np.zeros(total, dtype=bool)
    if total > 1:
        same[1:] = m[1:] == m[:-1]
        pairs = np.flatnonzero(same)
        for k in range(window):  # equal numbers must mean equal words
            wrong = code[st[pairs] + k] != code[st[pairs - 1] + k]
            if wrong.any():
                return _by_words(code, start, doc, of, inner, ths, firsts, docs, window)
    group = np.cumsum(~same)
    least = np.zeros(group[-1] + 1 if total else 1, dtype=np.int64)
    lead = np.flatnonzero(~same)
    least[group[lead]] = d[lead]
    dup = np.zeros(total, dtype=bool)
    dup[order] = d > least[group]
    return _as_marks(np.flatnonzero(dup), of, inner, docs, ths, firsts)


def _by_words(code, start, doc, of, inner, ths, firsts, docs, window):
    """The same by comparing whole rows of word numbers, for a bucket in which two sequences share a number."""
    least: dict = {}
    keys = [code[s : s + window].tobytes() for s in start]
    for k, d in zip(keys, doc.tolist()):
        least[k] = min(d, least.get(k, d))
    dup = np.array([d > least[k] for k, d in zip(keys, doc.tolist())])
    return _as_marks(np.flatnonzero(dup), of, inner, docs, ths, firsts)


def _as_marks(at, of, inner, docs, ths, firsts) -> dict:
    out: dict = {}
    if not len(at):
        return out
    o, i = of[at], inner[at]
    new = np.flatnonzero(np.r_[True, (o[1:] != o[:-1]) | (i[1:] != i[:-1] + 1)])
    ends = np.r_[new[1:], len(at)]
    for a, e in zip(new.tolist(), ends.tolist()):
        r = int(o[a])
        out.setdefault((docs[r], ths[r]), []).append((firsts[r] + int(i[a]), e - a))
    return out


def _single_windows(records, window: int):
    """(doc, th, first, hash) of every window of the records."""
    for doc, th, first, s in records:
        words = s.split()
        for k in range(len(words) - window + 1):
            yield doc, th, first + k, hashlib.blake2b(b" ".join(words[k : k + window]), digest_size=16).digest()


def _sweep_buckets(window: int, limit: int):
    """Blobs sorted by bucket -> (doc_id, th, marks, hash): marks, or (with a hash) a window still to be judged."""

    def emit(found: dict):
        keys = list(found)
        none = pa.nulls(len(keys), pa.binary())
        return pa.RecordBatch.from_arrays(
            [pa.array([k[0] for k in keys], pa.int64()), pa.array([k[1] for k in keys], pa.int32()), pa.array([_pack_marks(found[k]) for k in keys], pa.binary()), none],
            ["doc_id", "th", "marks", "hash"],
        )

    def pass_on(records):
        rows = list(_single_windows(records, window))
        for k in range(0, len(rows), 1 << 16):
            part = rows[k : k + (1 << 16)]
            yield pa.RecordBatch.from_arrays(
                [pa.array([r[0] for r in part], pa.int64()), pa.array([r[1] for r in part], pa.int32()), pa.array([_pack_marks([(r[2], 1)]) for r in part], pa.binary()), pa.array([r[3] for r in part], pa.binary())],
                ["doc_id", "th", "marks", "hash"],
            )

    @tidy
    def run(batches):
        unpack = zstandard.ZstdDecompressor()
        key, held, size = None, [], 0
        for b in batches:
            for k, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                if k != key:
                    if held and (found := _duplicate_windows(held, window)):
                        yield emit(found)
                    key, held, size = k, [], 0
                if blob[:1] == b"M":
                    found = {}
                    for doc, th, _, m in _records(blob, unpack):
                        found[(doc, th)] = [tuple(x) for x in np.frombuffer(m, dtype="<i4").reshape(-1, 2).tolist()]
                    yield emit(found)
                    continue
                records = list(_records(blob, unpack))
                size += sum(len(r[3]) for r in records)
                if size <= limit:
                    held.extend(records)
                else:  # also what is held already
                    yield from pass_on(held)
                    yield from pass_on(records)
                    held = []
        if held and (found := _duplicate_windows(held, window)):
            yield emit(found)

    return run


def _rewrite(window: int):
    """Rows sorted by (doc_id, th, kind): marks first, then the texts they belong to."""

    @tidy
    def run(batches):
        key, marks = None, []
        for b in batches:
            n_words, n_removed, kept = [], [], []
            docs, ths, kinds, blobs = (b.column(k).to_pylist() for k in range(4))
            rows = []
            for k, (doc, th, kind, data, text) in enumerate(zip(docs, ths, kinds, blobs, column_bytes(b, "text"))):
                if (doc, th) != key:
                    key, marks = (doc, th), []
                if kind == 0:
                    marks.append(data)
                    continue
                rows.append(k)
                words = (text or b"").split()
                if not marks or doc is None:
                    n_words.append(len(words))
                    n_removed.append(0)
                    kept.append(None if text is None else b" ".join(words))
                    continue
                spans = np.concatenate([np.frombuffer(m, dtype="<i4").reshape(-1, 2) for m in marks])
                edge = np.zeros(len(words) + 1, dtype=np.int32)
                np.add.at(edge, spans[:, 0], 1)
                np.add.at(edge, spans[:, 0] + spans[:, 1] + window - 1, -1)
                stays = np.cumsum(edge)[:-1] == 0
                n_words.append(len(words))
                n_removed.append(int(len(words) - stays.sum()))
                kept.append(b" ".join([words[i] for i in np.flatnonzero(stays).tolist()]))
            if rows:
                yield pa.RecordBatch.from_arrays(
                    [b.column(5).take(pa.array(rows)), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())],
                    ["row", "n_words", "n_removed", "kept"],
                )

    return run


def bucket_count(size: int, parts: int) -> int:
    """Buckets for ``size`` bytes of text."""
    return max(4 * parts, -(-OVERLAP * size // BUCKET))


def frequent_words(docs: DataFrame, size: int, sample: int = SAMPLE) -> list[tuple[int, int]]:
    """(hash, count) of the words most frequent in about ``sample`` of the ``size`` bytes of text, a choice of documents by hash."""
    some = docs.filter(F.pmod(F.xxhash64("doc_id", F.lit(9)), F.lit(max(1, -(-size // sample)))) == 0)
    words = some.select(F.explode(F.split("text", r"[\x20\x09-\x0D]+")).alias("w")).filter("w != ''")
    counts = words.groupBy(F.crc32(F.col("w").cast("binary")).alias("h")).agg(F.count("*").alias("n"))
    return [(r["h"], r["n"]) for r in counts.orderBy(F.desc("n"), "h").limit(FREQUENT).collect()]  # at most FREQUENT rows of two numbers


def remove_repeats(docs: DataFrame, window: int = WINDOW, buckets: int | None = None, held: int = HELD) -> DataFrame:
    """``docs`` with n_words, n_removed and kept (the words that stay, joined by one space)."""
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    ranks = _ranks(frequent_words(docs, size))
    if buckets is None:
        buckets = bucket_count(size, parts)
    names = [c for c in docs.columns if c not in ("n_words", "n_removed", "kept", "text")]
    base = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.hash("text").alias("th"), "text", F.struct(*[F.col(f"`{c}`") for c in names]).alias("row")
    )
    packed = base.select("doc_id", "th", "text").mapInArrow(_scatter(buckets, window, ranks), "bucket int, blob binary")
    swept = packed.repartition(parts, "bucket").sortWithinPartitions("bucket").mapInArrow(_sweep_buckets(window, held), "doc_id long, th int, marks binary, hash binary")
    swept = materialize(swept, "repeats")
    single = swept.filter("hash is not null")
    least = single.groupBy("hash").agg(F.min("doc_id").alias("least"), F.count("*").alias("n"))
    judged = spread_join(single, least, ["hash"], "n", single.count()).filter("doc_id > least")
    swept = swept.filter("hash is null").select("doc_id", "th", "marks").union(judged.select("doc_id", "th", "marks"))
    row = base.schema["row"].dataType
    marks = swept.select("doc_id", "th", F.lit(0).alias("kind"), "marks", F.lit(None).cast("string").alias("text"), F.lit(None).cast(row).alias("row"))
    texts = base.select("doc_id", "th", F.lit(1).alias("kind"), F.lit(None).cast("binary").alias("marks"), "text", "row")
    met = marks.union(texts).repartition(parts, "doc_id", "th").sortWithinPartitions("doc_id", "th", "kind")
    schema = T.StructType([T.StructField("row", row), T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept", T.StringType())])
    done = met.mapInArrow(_rewrite(window), schema)
    return done.select("row.*", "n_words", "n_removed", "kept")


def op9_substring_dedup(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = remove_repeats(docs)
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.coalesce("kept", F.lit("")), 256).alias("kept_sha256"))
