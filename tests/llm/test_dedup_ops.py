"""Line dedup, SimHash and substring dedup against brute force."""

import hashlib
import random
import re

import numpy as np
import pytest
import xxhash

from graphdist.llm import line_dedup, simhash_dedup, substring_dedup

WORDS = [f"w{i}{'xyz'[i % 3] * (i % 5)}" for i in range(400)]
SPACE = re.compile(r"[^\x20\x09-\x0D]+")


def sentence(r, n):
    return " ".join(r.choice(WORDS) for _ in range(n))


@pytest.fixture(scope="module")
def corpus():
    r = random.Random(5)
    passage, line = sentence(r, 40), sentence(r, 15)
    base = [sentence(r, 120) for _ in range(25)]
    rows = []
    for i in range(120):
        t = base[r.randrange(25)].split()
        for _ in range(r.randrange(3)):
            t[r.randrange(len(t))] = "changed"
        text = " ".join(t)
        if i % 4 == 0:
            text += "\n" + passage + "\n" + line
        rows.append((1000 - 3 * i, text))
    long = "\n".join(sentence(r, 12) for _ in range(3000))
    return rows + [(5000, None), (5001, ""), (5002, "   \n "), (5003, "Été ÉTÉ a\u00a0b"), (5004, long), (5005, long + " end"), (5006, "one"), rows[0]]


# fixed expectations of the fingerprint contract
def fp(text):
    w = SPACE.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return 0
    s = [" ".join(w[i : i + 4]) for i in range(len(w) - 3)] if len(w) >= 4 else [" ".join(w)]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def classes(n, linked):
    par = list(range(n))

    def root(x):
        while par[x] != x:
            x = par[x]
        return x

    for a, b in linked:
        a, b = root(a), root(b)
        par[max(a, b)] = min(a, b)
    return [root(x) for x in range(n)]


def test_simhash_matches_brute_force(corpus, make_docs):
    got = {r["doc_id"]: (r["fp"] & (2**64 - 1), r["component_id"]) for r in simhash_dedup.near_duplicate_groups(make_docs(corpus)).collect()}
    rows = sorted(set(corpus), key=lambda r: r[0])
    v = np.array([fp(t) for _, t in rows], dtype=np.uint64)
    c = classes(len(rows), [(i, j) for i in range(len(v)) for j in np.flatnonzero(np.bitwise_count(v ^ v[i]) <= 4).tolist() if i < j])
    assert got == {d: (int(x), rows[k][0]) for (d, _), x, k in zip(rows, v, c)}


def test_simhash_links_are_complete_on_random_fingerprints(spark):
    r = random.Random(2)
    seeds = [r.getrandbits(64) for _ in range(60)]
    fps = set(seeds)
    for s in seeds:
        for _ in range(6):
            x = s
            for b in r.sample(range(64), r.randrange(1, 6)):
                x ^= 1 << b
            fps.add(x)
    fps = sorted(fps)
    signed = [x - (1 << 64) if x >> 63 else x for x in fps]
    for block in (2048, 8):  # the second cuts cells into blocks
        found = [(r["a"], r["b"]) for r in simhash_dedup.links(spark.createDataFrame([(x,) for x in signed], "fp long"), block=block).collect()]
        at = {x: i for i, x in enumerate(signed)}
        v = np.array(fps, dtype=np.uint64)
        every = [(i, j) for i in range(len(v)) for j in np.flatnonzero(np.bitwise_count(v ^ v[i]) <= 4).tolist() if i < j]
        pairs = [(at[a], at[b]) for a, b in found]
        assert set(tuple(sorted(p)) for p in pairs) <= set(every)
        assert classes(len(v), pairs) == classes(len(v), every)


def test_simhash_keeps_one(corpus, make_docs):
    docs = make_docs(corpus + [(None, "x"), (None, "y")])
    out = simhash_dedup.keep_one_per_group(docs)
    assert out.columns == docs.columns
    kept = [r["doc_id"] for r in out.collect()]
    want = {r["component_id"] for r in simhash_dedup.near_duplicate_groups(docs.filter("doc_id is not null")).collect()}
    assert sorted(x for x in kept if x is not None) == sorted(want) and kept.count(None) == 2
    assert simhash_dedup.near_duplicate_groups(make_docs([])).isEmpty()


def windows_removed(rows):
    first = {}
    for d, t in rows:
        w = SPACE.findall(t or "")
        for i in range(len(w) - 12):
            k = tuple(w[i : i + 13])
            first[k] = min(d, first.get(k, d))
    out = {}
    for d, t in rows:
        w = SPACE.findall(t or "")
        hit = [False] * len(w)
        for i in range(len(w) - 12):
            if first[tuple(w[i : i + 13])] < d:
                hit[i : i + 13] = [True] * 13
        out[d] = (len(w), sum(hit), " ".join(x for x, h in zip(w, hit) if not h))
    return out


@pytest.mark.parametrize("buckets", [None, 1])
def test_substring_dedup_matches_brute_force(corpus, make_docs, buckets):
    docs = make_docs(corpus + [(None, corpus[0][1])])
    rows = substring_dedup.remove_repeats(docs, buckets=buckets).collect()
    want = windows_removed(corpus)
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept"] or "") for r in rows if r["doc_id"] is not None}
    assert got == want and len(rows) == len(corpus) + 1
    assert [r["n_removed"] for r in rows if r["doc_id"] is None] == [0]
    assert any(v[1] > 50 for v in want.values())


def test_substring_dedup_exact_when_numbers_collide():
    """The fallback that compares whole rows of word numbers gives the same marks."""
    r = random.Random(1)
    records = [(d, 0, 0, " ".join(r.choice("abc") for _ in range(20)).encode()) for d in range(60)]
    plain = substring_dedup._duplicate_windows(records, 3)
    real = np.random.default_rng
    try:
        substring_dedup.np.random.default_rng = lambda seed: type("Z", (), {"integers": staticmethod(lambda a, b, size, dtype: np.zeros(size, dtype))})
        forced = substring_dedup._duplicate_windows(records, 3)
    finally:
        substring_dedup.np.random.default_rng = real
    expand = lambda m: {(k, f + i) for k, v in m.items() for f, n in v for i in range(n)}
    assert expand(plain) == expand(forced) and plain


def test_substring_rows_that_share_an_id(make_docs):
    a, b = " ".join(WORDS[:30]), " ".join(WORDS[100:130])
    got = sorted((r["n_removed"], r["kept"]) for r in substring_dedup.remove_repeats(make_docs([(1, a), (2, a), (2, b), (2, a)])).collect())
    assert got == [(0, a), (0, b), (30, ""), (30, "")]
    assert substring_dedup.remove_repeats(make_docs([])).isEmpty()


def test_substring_dedup_passes_on_hot_buckets(make_docs, corpus):
    """A bucket that may not be held is counted window by window, with the same result."""
    key = lambda rows: sorted(((r["doc_id"], r["n_words"], r["n_removed"], r["kept"]) for r in rows), key=str)
    docs = make_docs(corpus)
    whole = key(substring_dedup.remove_repeats(docs, buckets=2).collect())
    assert whole == key(substring_dedup.remove_repeats(docs, buckets=2, held=500).collect()) and any(r[2] for r in whole)


def test_substring_buckets_stay_below_what_a_task_holds(spark, make_docs):
    r = random.Random(12)
    common, rare = [f"common{k}" for k in range(9)], iter(range(10**9))
    texts = [" ".join(r.choice(common) if r.random() < 0.7 else f"rare{next(rare)}" for _ in range(300)).encode() for _ in range(60)]
    size = sum(map(len, texts))
    docs = make_docs([(n, t.decode()) for n, t in enumerate(texts)])
    ranks = substring_dedup._ranks(substring_dedup.frequent_words(docs, size))
    strings = {}
    for t in texts:
        for _, _, v, s in substring_dedup._runs(t, 13, ranks):
            strings[v] = strings.get(v, 0) + len(s)
    # the strings are larger than the text: the buckets must be counted for them, and no frequent word may hold many
    assert sum(strings.values()) / substring_dedup.bucket_count(100 * size << 20, 1) * (100 << 20) <= 1.2 * substring_dedup.BUCKET
    assert max(strings.values()) < 0.02 * sum(strings.values())


def test_near_duplicates_keep_one_text_of_a_repeated_id(make_docs):
    a, b = "one two three four five six seven", "other words that stand quite alone here"
    rows = [(1, a), (1, b), (2, a), (3, b), (3, b), (None, a)]
    got = sorted(((r["doc_id"] or 0, r["text"]) for r in simhash_dedup.keep_one_per_group(make_docs(rows)).collect()))
    assert got == [(0, a), (1, a), (1, b)]


def shingles(line, w=line_dedup.WIDTH):
    u = line.encode("utf-16-be")
    return frozenset(u[2 * i : 2 * (i + w)] for i in range(max(1, len(u) // 2 - w + 1)))


def brute_lines(rows):
    """Kept lines by comparing all pairs of different lines."""
    occ = [(d, p, x.strip(" ")) for d, t in rows for p, x in enumerate((t or "").split("\n")) if x.strip(" ")]
    lines = sorted({x for _, _, x in occ})
    s = [shingles(x) for x in lines]
    near = [(i, j) for i in range(len(s)) for j in range(i) if min(len(s[i]), len(s[j])) >= 0.8 * max(len(s[i]), len(s[j])) and 9 * len(s[i] & s[j]) >= 4 * (len(s[i]) + len(s[j]))]
    cls = dict(zip(lines, classes(len(lines), near)))
    first = {}
    for d, p, x in sorted(occ):
        first.setdefault(cls[x], (d, p))
    gone = {(d, p) for d, p, x in occ if first[cls[x]] != (d, p)}
    return {d: "\n".join(x for p, x in enumerate((t or "").split("\n")) if (d, p) not in gone) for d, t in rows}


def test_line_dedup_against_brute_force(make_docs):
    r = random.Random(8)
    base = [sentence(r, r.randrange(4, 40)) for _ in range(40)]
    rows = []
    for d in range(80):
        out = []
        for _ in range(r.randrange(1, 8)):
            w = base[r.randrange(40)].split()
            if len(w) > 20 and r.random() < 0.5:
                w[r.randrange(len(w))] = "edited"
            out.append(" ".join(w))
        rows.append((d, "\n".join(out + [""] * (d % 2))))
    want = brute_lines(rows)
    from pyspark.sql import functions as F

    out = line_dedup.dedup_lines(make_docs(rows).withColumn("n_lines", F.lit("clash")))
    assert out.columns == [*make_docs([]).columns, "n_lines", "n_removed"]
    got = {x["doc_id"]: x["text"] for x in out.collect()}
    lines = lambda m: sum(len([x for x in t.split("\n") if x.strip()]) for t in m.values())
    assert set(got) == set(want)
    # MinHash may miss a few pairs at the threshold; it never removes more than brute force
    assert lines(want) <= lines(got) <= lines(want) + 0.02 * lines(dict(rows))
    assert sum(got[d] != want[d] for d in want) <= 3


def test_line_dedup_edge_cases(make_docs):
    rows = [(3, "same line here\nother"), (1, "same line here"), (2, None), (4, ""), (5, "\n \n"), (3, "same line here\nother"), (None, "other"), (6, "Ünï çödé 中文字符\U0001f600"), (7, "Ünï çödé 中文字符\U0001f600")]
    got = sorted(((r["doc_id"] is None, r["doc_id"] or 0), r["text"], r["n_lines"], r["n_removed"]) for r in line_dedup.dedup_lines(make_docs(rows)).collect() if r["text"] is not None)
    by = {k[1]: (t, n, m) for k, t, n, m in got if not k[0]}
    assert by[1][0] == "same line here" and by[3] == ("other", 2, 1) and by[4] == ("", 1, 0) and by[5] == ("\n \n", 3, 0)
    assert by[6][0] != "" and by[7] == ("", 1, 1)
    assert [t for k, t, _, _ in got if k[0]] == [""] and len(got) == len(rows) - 1
    assert line_dedup.dedup_lines(make_docs([])).isEmpty()


def test_line_dedup_links_rare_variants_of_a_template(make_docs, monkeypatch):
    monkeypatch.setattr(line_dedup, "_BLOCK", 8, raising=False)
    r = random.Random(11)
    rows = []
    for _ in range(4):
        template = sentence(r, 60)
        rows += [(len(rows) + k, template + " " + sentence(r, 16)) for k in range(9)]  # the head: alike by the template only
        for _ in range(30):
            tail = sentence(r, 16).split()
            for at, n in ((0, r.randrange(1, 8)), (15, r.randrange(1, 8))):
                line = " ".join([template, *tail[:at], "edited", *tail[at + 1 :]])
                rows += [(1000 + len(rows) + k, line) for k in range(n)]
    want = brute_lines(rows)
    got = {x["doc_id"]: x["text"] for x in line_dedup.dedup_lines(make_docs(rows)).collect()}
    assert sum(t != "" for t in want.values()) <= sum(t != "" for t in got.values()) <= sum(t != "" for t in want.values()) + 2


def test_native_plans_have_no_python(make_docs, corpus):
    from graphdist.plans import inspect

    assert inspect.counts(line_dedup._candidates(line_dedup._occurrences(make_docs(corpus)), 8, 7, 3))["python"] == 0
    assert inspect.counts(line_dedup._candidates(line_dedup._occurrences(make_docs(corpus)), 8, 7, 3))["cartesian"] == 0


def test_digest_is_sha256_of_kept():
    assert hashlib.sha256(b"").hexdigest().startswith("e3b0c442")


@pytest.mark.parametrize("split", [4096, 8])
def test_line_dedup_loses_no_pair_of_a_bucket(make_docs, monkeypatch, split):
    """Whatever the sketches propose, and however a bucket is dealt: lines that share a bucket and are similar enough are linked."""
    monkeypatch.setattr(line_dedup, "_APART", -1)
    monkeypatch.setattr(line_dedup, "_SPLIT", split)
    monkeypatch.setattr(line_dedup, "_SAMPLE", 1)
    r = random.Random(11)
    lines = []
    for _ in range(3):
        t = sentence(r, 30).split()
        for _ in range(25):
            x = list(t)
            for k in r.sample(range(30), r.randrange(1, 5)):
                x[k] = r.choice(WORDS)
            lines.append(" ".join(x))
    lines += ["ab " * n + "end" for n in (60, 61, 90)] + [sentence(r, 1), "one two"]
    docs = make_docs(list(enumerate(lines)))
    occ = line_dedup._occurrences(docs)
    at = {x["id"]: lines.index(x["line"]) for x in occ.select("id", "line").distinct().collect()}
    buckets = {}
    for x in line_dedup._signatures(occ, 8, 7, 3).select("id", "keys.bucket").collect():
        for b in x["bucket"]:
            buckets.setdefault(b, set()).add(at[x["id"]])
    s = [shingles(x) for x in lines]
    pairs = {(i, j) for m in buckets.values() for i in m for j in m if i < j and len(s[i] & s[j]) >= 0.8 * len(s[i] | s[j])}
    want = classes(len(lines), pairs)
    found = {}
    for x in line_dedup.line_components(docs).collect():
        found.setdefault(x["component"], set()).add(at[x["id"]])
    groups = {}
    for i, c in enumerate(want):
        groups.setdefault(c, set()).add(lines.index(lines[i]))
    assert sorted(map(sorted, found.values())) == sorted(sorted(g) for g in groups.values() if len(g) > 1) and len(pairs) > 30


def test_line_profiles_bound_the_shingles_from_both_sides(spark):
    texts = {1: "abc", 2: "ab" * 40, 3: "the quick brown fox jumps over the lazy dog", 4: "the quick brown fox jumped over the lazy dog", 5: "né😀 " * 9, 6: "x1y2z3" * 30 + "tail"}
    rows = spark.createDataFrame([(k, bytearray(v.encode("utf-16-be"))) for k, v in texts.items()], "id long, u binary")
    sets = {k: {b[i : i + 16] for i in range(0, max(len(b) - 16, 0) + 1, 2)} for k, b in ((k, v.encode("utf-16-be")) for k, v in texts.items())}
    got = {r["id"]: r for r in line_dedup._profiles(rows, 8).collect()}
    assert set(got) == set(texts)
    words = [f"b{k}" for k in range(line_dedup._WORDS_OF_BITS)]
    for a in texts:
        assert 1 <= got[a]["p"] <= len(sets[a]) <= got[a]["n"]
        assert sum(bin(got[a][w] & (2**64 - 1)).count("1") for w in words) == got[a]["p"]
        for b in texts:
            differ = sum(bin((got[a][w] ^ got[b][w]) & (2**64 - 1)).count("1") for w in words)
            assert differ <= len(sets[a] ^ sets[b]) and (a == b) == (differ == 0)
