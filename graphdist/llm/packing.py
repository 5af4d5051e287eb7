"""Best-fit packing of tokenised documents into sequences, improved by swap-based local search.

A document's ids are cut into pieces of at most ``capacity``; only longer documents are cut. Pieces are dealt by
hash (of their row number, too, so that repeated rows spread) to shards of about ``shard`` pieces. A shard packs its pieces by best fit in falling order of length; then
a local search works on the bins that are not full: it takes the emptiest one and moves one or two of its pieces into
another bin, or exchanges one for one, one for two or two for one with it, whenever that raises the sum of squared
fills; bins that run empty vanish. The search stops only at the lower bound or when no such exchange is left.

Defined cases: NULL text counts as empty, a document of one id; repeated rows are packed each; a NULL doc_id is
kept; an empty table gives an empty table.
"""

from __future__ import annotations

import bisect
import heapq
import re
import unicodedata
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from graphdist.llm.arrow_io import column_bytes, slices, tidy
from graphdist.runtime import materialize

CAPACITY, END_ID, SHARD = 4096, 1, 8192
SLICE = 8 << 20  # bytes of text numbered together
REMEMBERED = 500_000  # units, about 200 bytes each; beyond it only those of the last batch stay
_MARKS = re.compile(r"(?<![!-/:-@\[-`{-~])[!-&(-/:-@\[-`{-~]++(?!')")
_SAFE = "".join(map(chr, range(32, 127))) + "\n\t\r"
VOCABULARY = "word_bpe_49k.json"


class Encoder:
    """Ids of whole texts, remembering those of their units.

    The tokenizer lower-cases, and splits at white space and between letters and runs of marks; but for apostrophes no
    rule looks across these borders. So the ids of a plain text (``_is_plain``) are those of its lower-cased words and
    runs of marks in order, where a run beside an apostrophe stays with its word. The units of many texts are numbered
    by Arrow, each different one is looked up once, and the ids are gathered by number. Any other text is left
    to the tokenizer as it is.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.encode = getattr(self.tokenizer, "encode_batch_fast", self.tokenizer.encode_batch)
        self.known: dict[str, bytes] = {}
        self.safe = set(_SAFE)

    def _is_plain(self, text: str) -> bool:
        """Blanks, line feeds, ASCII without other controls, and letters that are composed and stay one letter."""
        if "<|" in text:
            return False
        if not self.safe.issuperset(text):
            for c in set(text) - self.safe:
                low = c.lower()
                if ord(c) < 128 or c == "\u03a3" or not c.isalpha() or len(low) != 1 or not low.isalpha() or unicodedata.normalize("NFC", c) != c:
                    return False
                self.safe.add(c)
        return text.isascii() or unicodedata.is_normalized("NFC", text)

    def _lookup(self, units: list[str]) -> list[bytes]:
        known = self.known
        new = [u for u in units if u not in known]
        for u, e in zip(new, self.encode(new, add_special_tokens=False) if new else ()):
            known[u] = np.array(e.ids, dtype="<u4").tobytes()
        found = list(map(known.__getitem__, units))
        if len(known) > REMEMBERED:
            self.known = dict(zip(units, found))
        return found

    def ids(self, texts: list[bytes]) -> list[bytes]:
        """Little-endian 32-bit ids of each text."""
        out: list[bytes] = [b""] * len(texts)
        plain, at = [], []
        for k, t in enumerate(texts):
            s = t.decode("utf-8", "replace")
            if self._is_plain(s):
                plain.append(_MARKS.sub(r" \g<0> ", s.lower()))
                at.append(k)
            else:
                out[k] = np.array(self.encode([s], add_special_tokens=False)[0].ids, dtype="<u4").tobytes()
        if not plain:
            return out
        lists = pc.ascii_split_whitespace(pa.array(plain, pa.large_string()))
        numbered = lists.flatten().dictionary_encode()
        units = numbered.dictionary.to_pylist()
        found = self._lookup(units)
        pool = np.frombuffer(b"".join(found), dtype="<u4")
        size = np.fromiter(map(len, found), dtype=np.int64, count=len(found)) // 4
        first = np.cumsum(size) - size
        code = numbered.indices.to_numpy(zero_copy_only=False)
        n = size[code]
        ends = np.cumsum(n)
        flat = pool[np.repeat(first[code] - (ends - n), n) + np.arange(int(ends[-1]) if len(ends) else 0)].tobytes()
        borders = np.concatenate([[0], ends])[lists.offsets.to_numpy() - lists.offsets[0].as_py()] * 4
        for k, a, b in zip(at, borders[:-1].tolist(), borders[1:].tolist()):
            out[k] = flat[a:b]
        return out


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str | None = None) -> Encoder:
    """One encoder a Python worker, kept from task to task: its memory of words is worth more than its space."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path(VOCABULARY)
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


def pieces(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, tokenizer: str | None = None) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32) of every piece."""

    @tidy
    def run(batches):
        coder = encoder(tokenizer)
        tail = np.array([end_id], dtype="<u4").tobytes()
        for whole in batches:
            for b in slices(whole, "text", SLICE):
                cols = [[], [], [], [], []]
                for doc, ids in zip(b.column(0).to_pylist(), coder.ids([t or b"" for t in column_bytes(b, "text")])):
                    ids += tail
                    for p, start in enumerate(range(0, len(ids), 4 * capacity)):
                        part = ids[start : start + 4 * capacity]
                        for c, v in zip(cols, (doc, p, start // 4, len(part) // 4, zlib.crc32(part))):
                            c.append(v)
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def best_fit(lengths: list[int], capacity: int) -> list[list[int]]:
    """Bins (lists of piece numbers) by best fit in falling order of length."""
    bins: list[list[int]] = []
    slacks: list[tuple[int, int]] = []  # (room, bin), sorted
    for k in sorted(range(len(lengths)), key=lambda k: (-lengths[k], k)):
        n = lengths[k]
        at = bisect.bisect_left(slacks, (n, -1))
        if at == len(slacks):
            bins.append([k])
            room, b = capacity - n, len(bins) - 1
        else:
            room, b = slacks.pop(at)
            bins[b].append(k)
            room -= n
        if room:
            bisect.insort(slacks, (room, b))
    return bins


class _Sums:
    """Lengths (or sums of two lengths) that each open bin can give, all bins in one flat array.

    A bin's values are distinct, so their number is bounded by the capacity, not by the pieces. Those of a
    changed bin are struck out and written anew at the end.
    """

    GONE = 1 << 40  # no exchange fits it, on either side

    def __init__(self):
        self.value, self.bin = np.full(1024, self.GONE, dtype=np.int64), np.zeros(1024, dtype=np.int64)
        self.at: dict[int, tuple[int, int]] = {}
        self.end = 0

    def put(self, b: int, values: np.ndarray) -> None:
        lo, hi = self.at.pop(b, (0, 0))
        self.value[lo:hi] = self.GONE
        if self.end + len(values) > len(self.value):
            self._tidy(len(values))
        if len(values):
            self.at[b] = (self.end, self.end + len(values))
            self.value[self.end : self.end + len(values)] = values
            self.bin[self.end : self.end + len(values)] = b
            self.end += len(values)

    def _tidy(self, room: int) -> None:
        parts = [(b, self.value[lo:hi]) for b, (lo, hi) in self.at.items()]
        size = 2 * (sum(len(v) for _, v in parts) + room) + 1024
        self.value, self.bin, self.at, self.end = np.full(size, self.GONE, dtype=np.int64), np.zeros(size, dtype=np.int64), {}, 0
        for b, v in parts:
            self.put(b, v)

    def of(self, b: int) -> np.ndarray:
        lo, hi = self.at.get(b, (0, 0))
        return self.value[lo:hi]


def local_search(bins: list[list[int]], lengths: list[int], capacity: int) -> list[list[int]]:
    """Empty the emptiest bins by moves and exchanges that raise the squared fill, until none is left.

    A bin is looked at in both roles, as giver and as taker, against all others at once. It comes up again only
    after it has changed: between two bins that were looked at and did not change there is no exchange.
    """
    bins = [list(b) for b in bins]
    fill = np.array([sum(lengths[k] for k in b) for b in bins], dtype=np.int64)
    least = -(-int(fill.sum()) // capacity)
    alive = sum(map(bool, bins))
    ones, twos = _Sums(), _Sums()
    queue: list[tuple[int, int]] = []
    waiting: set[int] = set()

    def changed(b):
        open_ = bool(bins[b]) and fill[b] < capacity
        held = sorted(lengths[k] for k in bins[b]) if open_ else []
        v = np.array(sorted({0, *held}) if open_ else [], dtype=np.int64)  # 0: nothing comes back
        ones.put(b, v)
        again = np.array(sorted({x for x, y in zip(held, held[1:]) if x == y}), dtype=np.int64)
        a, c = np.triu_indices(max(0, len(v) - 1), 1)
        twos.put(b, np.unique(np.concatenate([v[1:][a] + v[1:][c], 2 * again])))
        if open_:
            waiting.add(b)
            heapq.heappush(queue, (int(fill[b]), b))

    def pick(b, total):
        """One piece or two pieces of the bin with this sum."""
        if total == 0:
            return []
        seen: dict[int, int] = {}
        for k in bins[b]:
            if lengths[k] == total:
                return [k]
        for k in bins[b]:
            if total - lengths[k] in seen:
                return [seen[total - lengths[k]], k]
            seen.setdefault(lengths[k], k)
        raise AssertionError("no such pieces")

    def exchange(giver, taker, out, back):
        there, here = pick(giver, out), pick(taker, back)
        bins[giver] = [k for k in bins[giver] if k not in there] + here
        bins[taker] = [k for k in bins[taker] if k not in here] + there
        fill[giver] -= out - back
        fill[taker] += out - back
        changed(giver)
        changed(taker)

    def best(gain, ok):
        gain = np.where(ok, gain, 0)
        i = int(gain.argmax()) if len(gain) else 0
        return (int(gain[i]), i) if len(gain) else (0, 0)

    def look(b) -> bool:
        one, two = ones.of(b), twos.of(b)
        both = np.union1d(one, two)
        found = (0, None)
        for theirs, mine in ((ones, both), (twos, one)):  # b gives: the largest sum that still fits
            back, t = theirs.value[: theirs.end], theirs.bin[: theirs.end]
            out = mine[np.maximum(np.searchsorted(mine, back + capacity - fill[t], side="right") - 1, 0)]
            d = out - back
            gain, i = best(d * (fill[t] - fill[b] + d), (d > 0) & (t != b) & (fill[t] + d > fill[b]))
            if gain > found[0]:
                found = (gain, (b, int(t[i]), int(out[i]), int(back[i])))
        if found[1] is None:
            for theirs, mine in ((ones, both), (twos, one)):  # b takes, and gives back as little as makes room
                out, g = theirs.value[: theirs.end], theirs.bin[: theirs.end]
                i = np.searchsorted(mine, out - (capacity - fill[b]), side="left")
                back = mine[np.minimum(i, len(mine) - 1)]
                d = out - back
                gain, i = best(d * (fill[b] - fill[g] + d), (d > 0) & (d <= capacity - fill[b]) & (g != b) & (fill[b] + d > fill[g]))
                if gain > found[0]:
                    found = (gain, (int(g[i]), b, int(out[i]), int(back[i])))
        if found[1] is None:
            return False
        exchange(*found[1])
        return True

    if alive > least:
        for b in range(len(bins)):
            changed(b)
    while queue and alive > least:
        f, b = heapq.heappop(queue)
        if b not in waiting or f != fill[b]:
            continue
        waiting.discard(b)
        if look(b):
            alive = sum(map(bool, bins)) if fill.min() == 0 else alive
    return [b for b in bins if b]


def pack_shard(frame: pd.DataFrame, capacity: int) -> pd.DataFrame:
    frame = frame.sort_values(["doc_id", "piece", "start", "ids_crc32"], kind="stable").reset_index(drop=True)
    lengths = frame["length"].tolist()
    packed = local_search(best_fit(lengths, capacity), lengths, capacity)
    sequence, offset = np.zeros(len(frame), dtype=np.int64), np.zeros(len(frame), dtype=np.int64)
    for s, b in enumerate(packed):
        at = 0
        for k in b:
            sequence[k], offset[k] = s, at
            at += lengths[k]
    frame["sequence_id"] = frame["shard"].astype("int64") * 2**32 + sequence
    frame["offset"] = offset
    return frame[["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]]


def pack(docs: DataFrame, capacity: int = CAPACITY, shard: int = SHARD, tokenizer: str | None = None) -> DataFrame:
    """One row a piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    cut = materialize(pieces(docs, capacity, tokenizer=tokenizer), "pieces")
    n = max(1, -(-cut.count() // shard))
    dealt = cut.withColumn("shard", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32", F.monotonically_increasing_id()), F.lit(n)).cast("int"))
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
    none = F.expr("-9223372036854775807L - 1L")  # pandas would turn a NULL doc_id and all beside it into floats
    packed = dealt.withColumn("doc_id", F.coalesce("doc_id", none)).groupBy("shard").applyInPandas(lambda f: pack_shard(f, capacity), schema)
    return packed.withColumn("doc_id", F.nullif("doc_id", none))


def op3_packing(spark, sf_dir):
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
