"""Benchmark decontamination by Wu-Manber multi-pattern search over words.

Words: A-Z lower-cased, then ``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+``. A window is 13 consecutive words of an
item, or all words of a shorter one; a document word inside any occurrence of a window is hit.

The alphabet of the search is words, numbered as the benchmark knows them (0: unknown). Windows of one length are one pattern set with a
table of block shifts (a block is two neighbouring words, or one for windows of one word, at its hash; blocks that share a place take the
smaller shift): a block that no window holds lets the search skip a whole window less one block, any other block as far as the
nearest place it has in a window. At shift zero the suffix hash names a bucket of windows, found in a sorted table, and each
is compared directly, word by word.

The pattern sets are sent to the tasks in chunks of items whose text stays below ``max_bytes`` (checked by an
aggregation) and are built once a worker as flat arrays. If the benchmark is larger, each chunk is searched on its own pass and the
passes are combined by text.

Defined cases: NULL text has no words; an item without words has no window; repeated rows are judged each; an item without an id
hits words but is neither counted nor listed; an empty benchmark leaves every document clean; other columns pass through.
"""

from __future__ import annotations

import hashlib
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from graphdist.llm.arrow_io import column_bytes, slices, tidy
from graphdist.llm.skew import spread_join
from graphdist.runtime import materialize

WINDOW, SHARE, MAX_BYTES, SLICE = 13, 20, 16 << 20, 8 << 20
_TABLE = bytes(
    (c + 32) if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256)
)


def words_of(text: bytes | None) -> list[bytes]:
    return (text or b"").translate(_TABLE).split()


_MIX = np.random.default_rng(7).integers(1, 2**63, size=64, dtype=np.uint64) | np.uint64(1)


class PatternSet:
    """Windows of one length m in flat arrays: shifts by block hash, windows sorted by their hash, items of each."""

    def __init__(self, m: int, codes: np.ndarray, starts: np.ndarray, items: np.ndarray):
        self.m, self.block, self.codes = m, min(2, m), codes
        far = m - self.block + 1
        bits = max(10, min(26, int(np.ceil(np.log2(4 * len(starts) + 1)))))
        self.mask = np.uint64((1 << bits) - 1)
        self.shift = np.full(1 << bits, far, dtype=np.uint8 if far < 256 else np.int32)
        for gap in range(far - 1, -1, -1):  # the nearest place of a block counts
            self.shift[self._blocks(codes, starts + (m - gap - self.block))] = gap
        order = np.argsort(h := self._hashes(codes, starts), kind="stable")
        self.hash, self.start, self.item = h[order], starts[order], items[order]

    def _blocks(self, codes: np.ndarray, at: np.ndarray) -> np.ndarray:
        h = (codes[at].astype(np.uint64) + np.uint64(1)) * _MIX[0]
        if self.block == 2:
            h += (codes[at + 1].astype(np.uint64) + np.uint64(1)) * _MIX[1]
        return ((h ^ (h >> np.uint64(29))) * _MIX[2] >> np.uint64(20)) & self.mask

    def _hashes(self, codes: np.ndarray, at: np.ndarray) -> np.ndarray:
        h = np.zeros(len(at), dtype=np.uint64)
        for k in range(self.m):
            h = (h ^ (codes[at + k].astype(np.uint64) + np.uint64(1))) * _MIX[k % 64]
            h ^= h >> np.uint64(31)
        return h

    def search(self, codes: np.ndarray, hit: bytearray, items: set) -> None:
        m, n = self.m, len(codes)
        if n < m:
            return
        shifts = self.shift[self._blocks(codes, np.arange(n - self.block + 1))].tolist()
        back, end, found = self.block, m, []
        while end <= n:
            gap = shifts[end - back]
            if gap:
                end += gap
            else:
                found.append(end)
                end += 1
        if not found:
            return
        begin = np.array(found, dtype=np.int64) - m
        h = self._hashes(codes, begin)
        lo, hi = np.searchsorted(self.hash, h, side="left"), np.searchsorted(self.hash, h, side="right")
        for b, x, y in zip(begin.tolist(), lo.tolist(), hi.tolist()):
            window = codes[b : b + m]
            for k in range(x, y):
                s = int(self.start[k])
                if np.array_equal(self.codes[s : s + m], window):  # a window with an unknown word equals none
                    items.add(int(self.item[k]))
                    hit[b : b + m] = b"\x01" * m


class Patterns:
    """All pattern sets of a chunk of the benchmark, with its numbered words and item ids."""

    def __init__(self, items, window: int = WINDOW):
        self.number: dict[bytes, int] = {}
        self.ids: list = []
        codes, by = [], {}
        at = 0
        for item, text in items:
            words = words_of(text.encode() if isinstance(text, str) else text)
            if not words:
                continue
            m = min(window, len(words))
            starts, owners = by.setdefault(m, ([], []))
            starts.append(np.arange(at, at + len(words) - m + 1, dtype=np.int64))
            owners.append(np.full(len(words) - m + 1, len(self.ids), dtype=np.int32))
            codes.append(np.fromiter((self.number.setdefault(w, len(self.number) + 1) for w in words), dtype=np.int32, count=len(words)))
            self.ids.append(item)
            at += len(words)
        flat = np.concatenate(codes) if codes else np.zeros(0, dtype=np.int32)
        self.sets = [PatternSet(m, flat, np.concatenate(s), np.concatenate(o)) for m, (s, o) in by.items()]

    def hits(self, words: list[bytes]) -> tuple[bytearray, set]:
        """The hit words and the ids of the items whose windows occur."""
        hit, found = bytearray(len(words)), set()
        if words and self.sets:
            known = self.number.get
            codes = np.fromiter((known(w, 0) for w in words), dtype=np.int32, count=len(words))
            for s in self.sets:
                s.search(codes, hit, found)
        return hit, {self.ids[k] for k in found} - {None}


_BUILT: dict[str, Patterns] = {}


def _patterns(key: str, shared, window: int) -> Patterns:
    """The pattern sets of a broadcast chunk, built once a worker."""
    if key not in _BUILT:
        _BUILT.clear()
        _BUILT[key] = Patterns(shared.value, window)
    return _BUILT[key]


def _chunks(benchmark: DataFrame, max_bytes: int) -> list[DataFrame]:
    """The benchmark in pieces whose texts have at most about ``max_bytes`` together; one piece unless it is larger."""
    total = benchmark.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    if total <= max_bytes:
        return [benchmark]
    n = -(-2 * total // max_bytes)
    return [benchmark.filter(F.pmod(F.xxhash64("item_id"), F.lit(n)) == k) for k in range(n)]


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = SHARE, max_bytes: int = MAX_BYTES) -> DataFrame:
    """``docs`` with n_words, n_hit, n_items, items_sha256 and contaminated (n_hit > 0 and share * n_hit >= n_words)."""
    names = [c for c in docs.columns if c not in ("n_words", "n_hit", "n_items", "items_sha256", "contaminated")]
    docs = docs.select(*names)
    spark = docs.sparkSession
    chunks = _chunks(benchmark.select("item_id", "text"), max_bytes)
    if len(chunks) > 1:
        return _in_passes(docs, chunks, window, share)
    sets = spark.sparkContext.broadcast([(r.item_id, r.text) for r in chunks[0].collect()])
    at = names.index("text")
    schema = T.StructType(list(docs.schema.fields))
    for c in ("n_words", "n_hit", "n_items"):
        schema = schema.add(c, T.LongType())
    schema = schema.add("items_sha256", T.StringType()).add("contaminated", T.BooleanType())

    key = uuid.uuid4().hex

    @tidy
    def run(batches):
        patterns = _patterns(key, sets, window)
        for whole in batches:
            for b in slices(whole, "text", SLICE):
                cols = [[], [], [], [], []]
                for text in column_bytes(b, names[at]):
                    words = words_of(text)
                    hit, items = patterns.hits(words)
                    n = sum(hit)
                    ids = ",".join(sorted(map(str, items)))
                    for c, v in zip(cols, (len(words), n, len(items), hashlib.sha256(ids.encode()).hexdigest(), n > 0 and share * n >= len(words))):
                        c.append(v)
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_())
                yield pa.RecordBatch.from_arrays(
                    [*b.columns, *[pa.array(c, k) for c, k in zip(cols, kinds)]], [*b.schema.names, "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
                )

    return docs.mapInArrow(run, schema)


def _in_passes(docs: DataFrame, chunks: list[DataFrame], window: int, share: int) -> DataFrame:
    """One pass over the different texts for each chunk of the benchmark; the hit words and the items are united by text."""
    spark = docs.sparkSession
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.sha2("text", 256).alias("key"))
    found = None
    for chunk in chunks:
        sets, name = spark.sparkContext.broadcast([(r.item_id, r.text) for r in chunk.collect()]), uuid.uuid4().hex

        @tidy
        def run(batches, sets=sets, name=name):
            patterns = _patterns(name, sets, window)
            for whole in batches:
                for b in slices(whole, "text", SLICE):
                    keys, spans, ids = [], [], []
                    for key, text in zip(b.column(0).to_pylist(), column_bytes(b, "text")):
                        hit, items = patterns.hits(words_of(text))
                        if any(hit):
                            keys.append(key)
                            spans.append([k for k, x in enumerate(hit) if x])
                            ids.append([str(x) for x in items])
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(keys, pa.string()), pa.array(spans, pa.list_(pa.int32())), pa.array(ids, pa.list_(pa.string()))], ["key", "spans", "ids"]
                    )

        texts = keyed.filter("key is not null").select("key", F.col("row.text").alias("text")).dropDuplicates(["key"])
        part = materialize(texts.mapInArrow(run, "key string, spans array<int>, ids array<string>"), "contamination")
        found = part if found is None else found.union(part)
    merged = found.groupBy("key").agg(
        F.size(F.array_distinct(F.flatten(F.collect_list("spans")))).alias("hits"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))).alias("items")
    )
    held = keyed.groupBy("key").agg(F.count("*").alias("n"))
    total = docs.count()
    counted = spread_join(keyed, merged.join(held, "key"), ["key"], "n", total)
    lowered = F.translate("row.text", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    n_words = F.coalesce(F.size(F.filter(F.split(lowered, r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"), lambda w: w != "")), F.lit(0))
    n_words = F.when(F.col("row.text").isNull(), 0).otherwise(n_words).cast("long")
    n_hit = F.coalesce("hits", F.lit(0)).cast("long")
    return counted.select(
        *[F.col(f"row.`{c}`").alias(c) for c in docs.columns], n_words.alias("n_words"), n_hit.alias("n_hit"), F.coalesce(F.size("items"), F.lit(0)).cast("long").alias("n_items"),
        F.sha2(F.coalesce(F.array_join("items", ","), F.lit("")), 256).alias("items_sha256"), ((n_hit > 0) & (share * n_hit >= n_words)).alias("contaminated"),
    )


def keep_clean(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    return contamination(docs, benchmark, **options).filter(~F.col("contaminated")).select(*docs.columns)


def op7_decontaminate(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    bench = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return contamination(docs, bench).drop("text")
