"""Language identification: script ranges narrow the candidates, Viterbi over words labels spans.

Learning: character n-grams (1 to 4 code points of ``^word$``) and whole words of labelled documents are counted by
language into a hashed table of ``2**bits`` features; smoothed log probabilities, centred over the languages, are
the model. It is fitted on a bounded sample: about ``sample_rows`` labelled rows, chosen by a hash of doc_id.

Prediction: a word's score for a language is the sum over its features. A letter is what ``str.isalpha`` says. The script
of a word's first letter in a listed script (code point ranges) narrows the candidates to languages seen in that script; a word
in a listed script no language was seen in says nothing. A word with letters outside the ranges alone may be of any language. Viterbi with a penalty for each switch of language labels every word; neighbouring words of one label are
a span. The text's language is the one with most words; the score is the share of its words, tempered by how far
their mean score is from the next language.

Defined cases: NULL text or one without letters is ``und`` with score 0; words without letters join the span around
them; ties go to the language first in order; repeated rows are predicted each; with no labelled row every text is
``und``; an empty table gives an empty table; other columns pass through.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from graphdist.llm.arrow_io import slices, tidy

BITS, SAMPLE_ROWS, PENALTY, GRAMS, PIECE = 16, 20_000, 12.0, 4, 2 << 20

# fixed values: first code points of script ranges and the script that starts there (0 = none)
_SCRIPTS = (
    (0x0000, 0), (0x0041, 1), (0x005B, 0), (0x0061, 1), (0x007B, 0), (0x00AA, 1), (0x00AB, 0), (0x00BA, 1), (0x00BB, 0), (0x00C0, 1), (0x0370, 2),
    (0x0400, 3), (0x0530, 4), (0x0590, 5), (0x0600, 6), (0x0700, 0), (0x0900, 7), (0x0980, 8), (0x0A00, 9), (0x0A80, 10),
    (0x0B00, 11), (0x0B80, 12), (0x0C00, 13), (0x0C80, 14), (0x0D00, 15), (0x0E00, 16), (0x0E80, 17), (0x0F00, 18), (0x1000, 19),
    (0x10A0, 20), (0x1100, 21), (0x1200, 22), (0x1E00, 1), (0x1F00, 2), (0x2000, 0), (0x3040, 23), (0x3100, 0), (0x3400, 24),
    (0x4DC0, 0), (0x4E00, 24), (0xA000, 0), (0xAC00, 21), (0xD7B0, 0), (0xF900, 24), (0xFB00, 1), (0xFB50, 6), (0xFE00, 0), (0x20000, 24), (0x30000, 0),
)
_STARTS = np.array([a for a, _ in _SCRIPTS], dtype=np.uint32)
_KINDS = np.array([b for _, b in _SCRIPTS], dtype=np.int8)
OTHER, N_SCRIPTS = 25, 26  # OTHER: letters outside the ranges


def _script_table() -> np.ndarray:
    """The script of every code point; 0 for all that is no letter."""
    n = 0x110000
    kinds = _KINDS[np.searchsorted(_STARTS, np.arange(n, dtype=np.uint32), side="right") - 1]
    letter = np.fromiter((chr(c).isalpha() for c in range(n)), dtype=bool, count=n)
    return np.where(letter, np.where(kinds > 0, kinds, OTHER), 0).astype(np.int8)


_SCRIPT_OF = _script_table()


def _features(words: list[str], bits: int):
    """Hashed features of words: (feature numbers, first feature of each word, script of each word)."""
    joined = "".join(f"^{w}$" for w in words)
    code = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    sizes = np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 2
    ends = np.cumsum(sizes)
    starts = ends - sizes
    word = np.repeat(np.arange(len(words)), sizes)
    script_at = _SCRIPT_OF[code]
    edge = np.zeros(len(code), dtype=bool)
    edge[starts] = True
    edge[ends - 1] = True
    script_at[edge] = 0
    script = np.zeros(len(words), dtype=np.int8)
    other = np.flatnonzero(script_at == OTHER)
    script[word[other]] = OTHER
    letters = np.flatnonzero((script_at > 0) & (script_at != OTHER))
    script[word[letters][::-1]] = script_at[letters][::-1]
    c = code.astype(np.uint64) + np.uint64(1)
    shift = np.uint64(64 - bits)
    feats, owners = [], []
    h = np.zeros(len(c), dtype=np.uint64)
    room = ends[word] - np.arange(len(c))
    for n in range(1, GRAMS + 1):
        part = c[n - 1 :]
        h = h[: len(part)]
        h = (h ^ part) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(32)
        ok = room[: len(part)] >= n
        if n == 1:
            ok &= ~edge[: len(part)]
        feats.append(((h[ok] * np.uint64(0xD6E8FEB86659FD93 + 2 * n)) >> shift).astype(np.int32))
        owners.append(word[: len(part)][ok])
    whole = np.add.reduceat((c ^ np.uint64(0x55)) * (np.arange(len(c)) - starts[word] + 3).astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F), starts) if len(words) else np.zeros(0, np.uint64)
    whole = whole ^ (whole >> np.uint64(31))
    feats.append(((whole * np.uint64(0x9E3779B97F4A7C15)) >> shift).astype(np.int32))
    owners.append(np.arange(len(words)))
    feat, owner = np.concatenate(feats), np.concatenate(owners)
    return feat, owner, script


class Model:
    """Languages, feature weights (features x languages) and the scripts of each language."""

    def __init__(self, langs: list[str], counts: np.ndarray, scripts: np.ndarray, bits: int):
        self.langs, self.bits = langs, bits
        smooth = counts + 0.5
        logs = np.log(smooth / smooth.sum(axis=0, keepdims=True))
        self.weights = (logs - logs.mean(axis=1, keepdims=True)).astype(np.float32) if langs else logs.astype(np.float32)
        share = scripts / np.maximum(1, scripts.sum(axis=0, keepdims=True))
        self.candidates = share >= 0.01  # scripts x languages
        self.candidates[OTHER] = True

    def score(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(scores, says) of distinct words; a word that says nothing has zero scores."""
        feat, owner, script = _features(words, self.bits)
        out = np.empty((len(words), len(self.langs)), dtype=np.float32)
        for k in range(len(self.langs)):
            out[:, k] = np.bincount(owner, weights=self.weights[feat, k], minlength=len(words))
        allowed = self.candidates[script]
        says = (script > 0) & allowed.any(axis=1)
        out = np.where(allowed, out, np.float32(-60.0))
        out[~says] = 0.0
        return out, script > 0


def label_words(texts: list[str | None], model: Model, penalty: float = PENALTY):
    """For each text (labels of its words, mean score by language over its lettered words, lettered words).

    All texts advance together, one word a step, so that a step costs one set of array operations.
    """
    split = [t.split() if t else [] for t in texts]
    flat = [w.lower() for ws in split for w in ws]
    sizes = np.array([len(ws) for ws in split], dtype=np.int64)
    if not flat or not model.langs:
        lettered = np.zeros(len(texts), dtype=np.int64)
        return [np.zeros(n, dtype=np.int8) for n in sizes], np.zeros((len(texts), len(model.langs))), lettered
    number: dict[str, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in flat), dtype=np.int64, count=len(flat))
    scores, letters = model.score(list(number))
    L = len(model.langs)
    order = np.argsort(-sizes, kind="stable")
    begin = np.cumsum(sizes) - sizes
    b, n = begin[order], sizes[order]
    live = np.searchsorted(-n, -np.arange(int(n[0])), side="left")  # texts with more than t words
    state = np.zeros((len(texts), L), dtype=np.float32)
    back = np.zeros((len(flat), L), dtype=np.int8)
    for t in range(int(n[0])):
        m = int(live[t])
        rows = b[:m] + t
        prev = state[:m]
        best = prev.argmax(axis=1)
        jump = prev[np.arange(m), best] - penalty
        stay = prev >= jump[:, None]
        back[rows] = np.where(stay, np.arange(L, dtype=np.int8), best[:, None].astype(np.int8))
        state[:m] = np.maximum(prev, jump[:, None]) + scores[ids[rows]]
    label = np.zeros(len(flat), dtype=np.int8)
    now = state.argmax(axis=1).astype(np.int8)
    for t in range(int(n[0]) - 1, -1, -1):
        m = int(live[t])
        rows = b[:m] + t
        label[rows] = now[:m]
        now[:m] = back[rows, now[:m]]
    has = letters[ids]
    owner = np.repeat(np.arange(len(texts)), sizes)
    lettered = np.bincount(owner, weights=has, minlength=len(texts)).astype(np.int64)
    means = np.stack([np.bincount(owner, weights=scores[ids, k], minlength=len(texts)) for k in range(L)], axis=1) / np.maximum(1, lettered)[:, None]
    words_by = np.stack([np.bincount(owner, weights=has & (label == k), minlength=len(texts)) for k in range(L)], axis=1)
    cut = np.split(label, np.cumsum(sizes)[:-1])
    return cut, (means, words_by), lettered


def predict(texts: list[str | None], model: Model, penalty: float = PENALTY):
    """(language, score, spans) of each text; a span is (first word, number of words, language)."""
    labels, sums, lettered = label_words(texts, model, penalty)
    out = []
    for k, lab in enumerate(labels):
        if not lettered[k] or not model.langs:
            out.append(("und", 0.0, []))
            continue
        means, by = sums[0][k], sums[1][k]
        top = int(by.argmax())
        rest = np.delete(means, top)
        margin = float(means[top] - rest.max()) if len(rest) else 10.0
        trust = 1.0 / (1.0 + np.exp(-np.clip(margin, -30, 30)))
        edges = np.flatnonzero(np.r_[True, lab[1:] != lab[:-1]])
        sizes = np.diff(np.r_[edges, len(lab)])
        spans = [(int(a), int(n), model.langs[int(lab[a])]) for a, n in zip(edges, sizes)]
        out.append((model.langs[top], float(min(1.0, max(0.0, by[top] / lettered[k] * trust))), spans))
    return out


def train(labelled: DataFrame, bits: int = BITS, sample_rows: int = SAMPLE_ROWS) -> Model:
    """Fit on about ``sample_rows`` rows of (doc_id, text, lang) with a language, drawn by a hash of doc_id."""
    rows = labelled.filter("lang is not null and text is not null")
    total = rows.count()
    if total > sample_rows:
        rows = rows.filter(F.pmod(F.xxhash64("doc_id", F.lit("sample")), F.lit(1_000_003)) < int(1_000_003 * sample_rows / total))

    @tidy
    def count(batches):
        sums: dict = {}
        for whole in batches:
            for b in slices(whole, "text", PIECE):
                by: dict = {}
                for lang, text in zip(b.column(1).to_pylist(), b.column(0).to_pylist()):
                    by.setdefault(lang, []).extend(w.lower() for w in text.split())
                for lang, words in by.items():
                    if words:
                        feat, _, script = _features(words, bits)
                        f, s = sums.setdefault(lang, (np.zeros(1 << bits), np.zeros(N_SCRIPTS)))
                        f += np.bincount(feat, minlength=1 << bits)
                        s += np.bincount(script, minlength=N_SCRIPTS)
        for lang, (f, s) in sums.items():
            whole = np.concatenate([f, s])
            at = np.flatnonzero(whole)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at)), pa.array(at, pa.int32()), pa.array(whole[at], pa.float64())], ["lang", "feature", "n"])

    counted = rows.select("text", "lang").mapInArrow(count, "lang string, feature int, n double").groupBy("lang", "feature").agg(F.sum("n").alias("n"))
    found = counted.toPandas()  # at most (2**bits + scripts) rows a language
    langs = sorted(found["lang"].unique().tolist())
    counts = np.zeros(((1 << bits) + N_SCRIPTS, len(langs)))
    if langs:
        counts[found["feature"].to_numpy(), found["lang"].map({x: k for k, x in enumerate(langs)}).to_numpy()] = found["n"].to_numpy()
    return Model(langs, counts[: 1 << bits], counts[1 << bits :], bits)


def identify(docs: DataFrame, model: Model, penalty: float = PENALTY, spans: bool = True) -> DataFrame:
    """``docs`` with lang_pred, score and (``spans``) the labelled spans of its words."""
    names = [c for c in docs.columns if c not in ("lang_pred", "score", "spans")]
    docs = docs.select(*names)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType(list(docs.schema.fields)).add("lang_pred", T.StringType()).add("score", T.DoubleType())
    kind = pa.list_(pa.struct([("first", pa.int32()), ("words", pa.int32()), ("lang", pa.string())]))
    if spans:
        schema = schema.add("spans", T.ArrayType(T.StructType().add("first", T.IntegerType()).add("words", T.IntegerType()).add("lang", T.StringType())))

    @tidy
    def run(batches):
        for whole in batches:
            for b in slices(whole, "text", PIECE):
                found = predict(b.column(b.schema.get_field_index("text")).to_pylist(), shared.value, penalty)
                extra = [pa.array([x[0] for x in found], pa.string()), pa.array([x[1] for x in found], pa.float64())]
                if spans:
                    extra.append(pa.array([[{"first": a, "words": n, "lang": g} for a, n, g in x[2]] for x in found], kind))
                yield pa.RecordBatch.from_arrays([*b.columns, *extra], [*b.schema.names, "lang_pred", "score", *["spans"] * spans])

    return docs.mapInArrow(run, schema)


def held_out(doc_id):
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(3)) == 1


def keep_identified(docs: DataFrame, model: Model, least: float = 0.0) -> DataFrame:
    """Documents with a known language (and a score of at least ``least``); the others are rejected."""
    found = identify(docs, model, spans=False)
    return found.filter((F.col("lang_pred") != "und") & (F.col("score") >= least)).select(*docs.columns)


def op10_language_id(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = F.coalesce(held_out(F.col("doc_id")), F.lit(False))
    model = train(docs.select("doc_id", "text", "lang").filter(~out))
    return identify(docs.select("doc_id", "text"), model, spans=False).select("doc_id", out.alias("held_out"), "lang_pred", "score")
