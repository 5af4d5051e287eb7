import re

import pytest
from helpers import GRAPHS, adjacency, all_pairs, bfs, gateway_labels, some_path_labels
from pyspark.sql import functions as F

from graphdist import datasets
from graphdist.baselines import full_table, independent_set, mask_hybrid, online, two_hop
from graphdist.operators import bfs as search_levels
from graphdist.operators import codec, gateway, graph, landmarks as lmk, metrics, query, search, verify
from graphdist.operators.components import connected_components
from graphdist.operators.engine import Index
from graphdist.runtime import cut

EXAMPLE = list(datasets.EXAMPLE14)
MARKS = list(datasets.EXAMPLE14_LANDMARKS)


def edges(spark, raw):
    return cut(graph.build(spark.createDataFrame(raw, "src long, dst long")))


def rows(df, *names):
    return {tuple(r[n] for n in names) for r in df.collect()}


def pairs_frame(spark, near):
    vs = sorted(near)
    return cut(spark.createDataFrame([(i, s, t) for i, (s, t) in enumerate((s, t) for s in vs for t in vs)], "pair_id long, s long, t long"))


@pytest.fixture(scope="module")
def example(spark):
    e = edges(spark, EXAMPLE)
    return Index.build(e, lmk.explicit(spark, MARKS))


def test_worked_example_labels(example):
    got = rows(example.labels, "v", "lm", "d")
    assert len(got) == 13
    assert got == gateway_labels(adjacency(EXAMPLE), MARKS)
    assert {v for v, r, _ in got if r == 1} == {4, 11, 13, 14}
    assert {v for v, r, _ in got if r == 5} == {2, 3, 7, 8, 12}
    assert {r for v, r, _ in got if v == 7} == {5, 9}
    assert {(1, 5, 1), (1, 9, 1), (5, 9, 2)} <= rows(example.matrix, "lm_a", "lm_b", "d")


def test_worked_example_query(spark, example):
    p = spark.createDataFrame([(0, 2, 11)], "pair_id long, s long, t long")
    r = example.distance(p).first()
    assert (r["ub"], r["dist"]) == (3, 3)
    near = rows(example.core.filter("src in (2, 11)"), "src", "dst")
    assert {b for a, b in near if a == 2} == {7, 12, 14} and {b for a, b in near if a == 11} == {4, 10}


def test_worked_example_two_orders(spark, example):
    for order, size, inner in (((1, 5, 9), 25, 20), ((9, 5, 1), 30, 24)):
        lab = two_hop.pruned_two_hop(example.edges, lmk.explicit(spark, order))
        got = rows(lab, "v", "lm", "d")
        assert len(got) == size and len({x for x in got if x[0] not in MARKS}) == inner
        assert {(r, d) for v, r, d in got if v == 11} == ({(1, 1)} if order[0] == 1 else {(1, 1), (5, 2), (9, 2)})


def test_example_all_pairs_exact_and_symmetric(spark, example):
    near = adjacency(EXAMPLE)
    truth = all_pairs(near)
    got = example.distance(pairs_frame(spark, near)).collect()
    assert all(r["dist"] == truth[r["s"], r["t"]] and r["ub"] >= r["dist"] for r in got)
    assert sum(r["dist"] for r in got) == 436
    inner = [r for r in got if r["s"] < r["t"] and r["s"] not in MARKS and r["t"] not in MARKS]
    assert len(inner) == 55 and sum(r["covered"] for r in inner) == 34 and sum(r["ub"] - r["dist"] for r in inner) == 36


@pytest.mark.parametrize("name", sorted(GRAPHS))
def test_small_graphs(spark, name):
    raw = GRAPHS[name]
    near, truth = adjacency(raw), all_pairs(adjacency(raw))
    e = edges(spark, raw + [(b, a) for a, b in raw[:2]] + [(raw[0][0], raw[0][0])])  # repeats, reversals, a loop
    for k in {1, max(1, len(near) - 1)}:
        index = Index.build(e, k)
        marks = [r["id"] for r in index.landmarks.collect()]
        assert rows(index.labels, "v", "lm", "d") == gateway_labels(near, marks)
        got = index.distance(pairs_frame(spark, near)).collect()
        assert all(r["dist"] == truth.get((r["s"], r["t"])) for r in got), (name, k)
        assert all((r["ub"] is None) or r["dist"] is not None and r["ub"] >= r["dist"] for r in got)


def test_builds_agree_and_order_does_not_matter(spark):
    e = edges(spark, GRAPHS["grid5"] + [(24, 40), (40, 41), (41, 0)])
    r = lmk.explicit(spark, [0, 12, 24, 40])
    want = gateway_labels(adjacency(GRAPHS["grid5"] + [(24, 40), (40, 41), (41, 0)]), [0, 12, 24, 40])
    for mode in ("masks", "sequential", "rows"):
        labels, matrix = gateway.build(e, r, mode)
        assert rows(labels, "v", "lm", "d") == want, mode
        full = search_levels.levels(e, r)
        assert rows(matrix, "lm_a", "lm_b", "d") == rows(gateway.matrix_from_full(full, r), "lm_a", "lm_b", "d")
    assert rows(gateway.build(e, lmk.reordered(r))[0], "v", "lm", "d") == want
    assert rows(gateway.from_full(full, r), "v", "lm", "d") == want
    assert verify.cover(*gateway.build(e, r), full, r).isEmpty() and verify.redundant(*gateway.build(e, r)).isEmpty()


def test_wrong_variants_are_told_apart(spark):
    near = adjacency(GRAPHS["two_ways"])
    assert gateway_labels(near, [0, 1]) != some_path_labels(near, [0, 1])  # 3 has a second way to 0, by landmark 1
    e = edges(spark, GRAPHS["two_ways"])
    assert rows(gateway.build(e, lmk.explicit(spark, [0, 1]))[0], "v", "lm", "d") == gateway_labels(near, [0, 1])
    # without closure of the matrix: the ends of a chain of landmarks are no direct pair
    path = edges(spark, GRAPHS["path10"])
    m = {(a, b): d for a, b, d in rows(gateway.build(path, lmk.explicit(spark, [1, 4, 8]))[1], "lm_a", "lm_b", "d")}
    assert m[1, 8] == 7
    # a drained search means the bound, not infinity: a star's core has no edge
    star = Index.build(edges(spark, GRAPHS["star"]), 1)
    r = star.distance(spark.createDataFrame([(0, 1, 2)], "pair_id long, s long, t long")).first()
    assert (r["core_d"], r["dist"]) == (None, 2)


def test_bounds(spark, example):
    near = adjacency(EXAMPLE)
    p = pairs_frame(spark, near)
    cross, pruned = (rows(example.upper_bound(p, m), "pair_id", "ub") for m in ("cross", "pruned"))
    assert cross == pruned
    full = search_levels.levels(example.edges, example.landmarks)
    truth = all_pairs(near)
    for r in query.triangle_bounds(p, full).collect():
        assert r["lower"] <= truth[r["s"], r["t"]] <= r["upper"] or r["s"] == r["t"]


def test_search_respects_any_bound(spark, example):
    near = {v: {w for w in ws if w not in MARKS} for v, ws in adjacency(EXAMPLE).items() if v not in MARKS}
    truth = all_pairs(near)
    p = pairs_frame(spark, near)
    for ub in (1, 2, 3):
        got = search.bounded_value(example.core, p.withColumn("ub", F.lit(ub))).collect()
        assert all(r["value"] == min(ub, truth.get((r["s"], r["t"]), ub)) for r in got)


def test_size_order_of_methods(spark):
    raw = GRAPHS["grid5"]
    e = edges(spark, raw)
    r = lmk.explicit(spark, [0, 7, 12, 18])
    full = cut(search_levels.levels(e, r))
    outside = lambda df: df.filter(~F.col("v").isin(0, 7, 12, 18)).count()
    a = gateway.build(e, r)[0].count()
    for order in (r, lmk.reordered(r)):
        b = outside(two_hop.pruned_two_hop(e, order))
        c = two_hop.pruned_cover(e, order, gateway.matrix_from_full(full, r)).count()
        assert a <= c <= outside(full) and a <= b <= outside(full)
        assert rows(two_hop.pruned_two_hop(e, order), "v", "lm", "d") == rows(two_hop.pruned_from_full(full, order), "v", "lm", "d")
    assert full_table.full_table(e, r).count() == 4 * 21


def test_baselines_are_exact(spark):
    raw = GRAPHS["cycle9"] + GRAPHS["two_triangles"][3:] + [(0, 4)]
    near = adjacency(raw)
    truth = all_pairs(near)
    e, p = edges(spark, raw), pairs_frame(spark, near)
    roots = mask_hybrid.default_roots(e, 2)
    masks = cut(mask_hybrid.labels(e, roots))
    for name, got in {
        "bidirectional": online.bidirectional(e, p), "one_sided": online.one_sided(e, p), "independent_set": independent_set.distance(e, p),
        "mask_hybrid": mask_hybrid.distance(e, roots, masks, p),
    }.items():
        assert all(r["dist"] == truth.get((r["s"], r["t"])) for r in got.collect()), name
    complete = cut(two_hop.complete(e))
    assert all(r["d"] == truth.get((r["s"], r["t"])) for r in query.two_hop(p, complete).collect())
    assert rows(search_levels.relax(e.withColumn("w", F.lit(2)), 0), "v", "d") == {(v, 2 * d) for v, d in bfs(near, 0).items()}


def test_masks_are_distance_differences(spark):
    raw = EXAMPLE
    near = adjacency(raw)
    e = edges(spark, raw)
    roots = mask_hybrid.default_roots(e, 2)
    chosen = {(r["lm"], r["bit"]): r["u"] for r in mask_hybrid.choose_neighbours(e, roots).collect()}
    for r in mask_hybrid.labels(e, roots).collect():
        for (lm, bit), u in chosen.items():
            if lm == r["lm"]:
                diff = bfs(near, u)[r["v"]] - r["d"]
                assert bool(r["m1"] >> bit & 1) == (diff == -1) and bool(r["m0"] >> bit & 1) == (diff == 0 and r["d"] > 0)


def test_pruned_labels_with_masks_are_exact(spark):
    raw = [(0, 1), (1, 2), (2, 3)]
    near = adjacency(raw)
    truth = all_pairs(near)
    e, p = edges(spark, raw), pairs_frame(spark, near)
    order = cut(lmk.top_degree(e, 4))
    masks = cut(mask_hybrid.labels(e, cut(order.filter("rank < 1")), width=1))
    lab = two_hop.pruned_two_hop(e, order.filter("rank >= 1"), mask_hybrid.pruning(masks))
    both = query.two_hop(p, lab).join(mask_hybrid.upper_bound(p, masks).select("pair_id", "ub"), "pair_id")
    assert all(min(x for x in (r["d"], r["ub"]) if x is not None) == truth[r["s"], r["t"]] for r in both.collect())
    assert lab.count() <= 6


def test_pruned_labels_after_masks_need_no_search(spark, monkeypatch):
    import random

    monkeypatch.setattr(two_hop, "_levels", None)
    r = random.Random(7)
    for raw in (EXAMPLE, [(r.randrange(30), r.randrange(30)) for _ in range(45)]):
        near, e = adjacency(raw), edges(spark, raw)
        order = cut(lmk.top_degree(e, 4))
        ids = [x["id"] for x in order.orderBy("rank").collect()]
        roots = cut(order.filter("rank < 1"))
        hubs = {ids[0]} | {x["u"] for x in mask_hybrid.choose_neighbours(e, roots, 2).collect()}
        want = set()
        for i, lm in enumerate(ids[1:]):
            away = {h: bfs(near, h) for h in hubs | set(ids[1 : 1 + i])}
            want |= {(v, lm, d) for v, d in bfs(near, lm).items() if v == lm or not any(lm in x and x[lm] + x[v] <= d for x in away.values())}
        after = cut(order.filter("rank >= 1"))
        got = two_hop.pruned_after_masks(cut(search_levels.levels(e, after)), after, cut(mask_hybrid.labels(e, roots, width=2)))
        assert sorted((x["v"], x["lm"], x["d"]) for x in got.collect()) == sorted(want)


def test_pruned_labels_of_a_vertex_meet_in_one_row(spark):
    """No landmark's distances are joined with those of every other: the only exchange is by vertex."""
    e = edges(spark, GRAPHS["grid5"])
    r = lmk.explicit(spark, [0, 7, 12, 18])
    plan = two_hop.pruned_from_full(cut(search_levels.levels(e, r)), r)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and plan.count("Exchange hashpartitioning") == 1


def test_levels_by_masks(spark):
    """All sources in one mask, more than a word of them, parts that no source reaches; a level is stored once a vertex."""
    raw = GRAPHS["grid5"] + [(100, i) for i in range(101, 165)] + [(0, 70)]
    near, e = adjacency(raw), edges(spark, raw)
    for ids in ([0, 12, 100], [*range(25), *range(100, 144)], []):
        got = [tuple(x) for x in search_levels.levels_by_masks(e, lmk.explicit(spark, ids)).select("lm", "v", "d").collect()]
        assert sorted(got) == sorted((s, v, d) for s in ids for v, d in bfs(near, s).items())


def test_codec(spark, example):
    for bits in (8, 32):
        back = codec.unpack(codec.pack(example.labels, example.landmarks, bits), example.landmarks, bits)
        assert rows(back, "v", "lm", "d") == rows(example.labels, "v", "lm", "d")
    path = edges(spark, [(i, i + 1) for i in range(300)])
    r = lmk.explicit(spark, [0])
    far = search_levels.levels(path, r).select("v", "lm", "d").filter("v != 0")
    with pytest.raises(Exception, match="distance exceeds 8 bits"):
        codec.pack(far, r).collect()
    assert codec.unpack(codec.pack(far, r, dist_bits=16), r, dist_bits=16).count() == 300


def test_empty_graph_and_measures(spark, example):
    e = edges(spark, [])
    index = Index.build(e, lmk.explicit(spark, []))
    assert index.labels.isEmpty()
    m = metrics.als(example.labels, example.edges, example.landmarks).first()
    assert (m["entries"], m["labelled"]) == (13, 11)
    assert metrics.graph_bytes(example.edges).first()[0] == 24 * 8
    assert metrics.mask_bytes(10, 2) == 420 and metrics.ratio(1, 0) is None


def test_components(spark):
    import random

    r = random.Random(3)
    raw = [(r.randrange(300), r.randrange(300)) for _ in range(180)] + [(0, i) for i in range(400, 460)] + [(i, i + 1) for i in range(1000, 1060)]
    near = adjacency(raw)
    got = rows(connected_components(spark.createDataFrame(raw, "a long, b long")), "id", "component")
    assert got == {(v, min(bfs(near, v))) for v in near}
    assert connected_components(spark.createDataFrame([], "a long, b long")).isEmpty()


def test_ranked_ids_and_pairs(spark):
    ids = spark.range(1, 500, 3).withColumnRenamed("id", "id")
    got = sorted(rows(graph.ranked(ids), "rank", "id"))
    assert got == list(enumerate(range(1, 500, 3)))


def test_local_search_leaves_the_graph_off_the_driver(spark, monkeypatch):
    from graphdist.operators import local_search

    edges = cut(graph.build(spark.createDataFrame(GRAPHS["grid5"], "src long, dst long")))
    truth = all_pairs(adjacency(GRAPHS["grid5"]))
    pairs = spark.createDataFrame([(n, s, t, None if n % 2 else 3) for n, (s, t) in enumerate(truth)] + [(9999, 0, 77, None)], "pair_id long, s long, t long, ub int")

    def refuse(self):
        raise AssertionError("the graph was collected")

    monkeypatch.setattr(type(edges), "toPandas", refuse)
    monkeypatch.setattr(local_search, "GROUP", 100)
    got = {r["pair_id"]: r["core_d"] for r in local_search.bounded(edges, pairs).collect()}
    want = {n: d if n % 2 or d <= 3 else None for n, d in enumerate(truth.values())}
    assert got == want | {9999: None}


def test_peeling_keeps_no_level_that_is_done(spark, tmp_path, monkeypatch):
    """Labels without the residual graph: least ways up as by plain search, and on disk only the rows of the removed vertices."""
    monkeypatch.setattr("graphdist.runtime.checkpoint_dir", lambda _: str(tmp_path))
    raw = [(i, (i * 7 + 3) % 40) for i in range(40)] + [(i, (i * 11 + 5) % 40) for i in range(40)] + [(50, 51), (51, 52)]
    e = graph.build(spark.createDataFrame(raw, "src long, dst long"))
    ups, residual = independent_set.peel(e, residual=False)
    stars = ups.collect()
    assert residual is None and len({r["level"] for r in stars}) > 1
    assert len(list(tmp_path.glob("graphdist-peel-*"))) <= len({r["level"] for r in stars}) + 1
    want, above = {}, {}
    for r in stars:
        above.setdefault(r["v"], []).append((r["up"], r["w"]))
    for v in {x for r in raw for x in r if r[0] != r[1]}:
        best, todo = {v: 0}, [v]
        while todo:
            x = todo.pop()
            for up, w in above.get(x, []):
                if best[x] + w < best.get(up, 10**9):
                    best[up] = best[x] + w
                    todo.append(up)
        want |= {(v, up): d for up, d in best.items()}
    got = independent_set.labels(ups, graph.vertices(e)).collect()
    assert len(got) == len(want) and {(r["v"], r["anc"]): r["d"] for r in got} == want


def test_dealt_edges_are_read_in_place(spark):
    near = adjacency(GRAPHS["grid5"])
    e = edges(spark, GRAPHS["grid5"])
    held = lambda: spark.sparkContext._jsc.getPersistentRDDs().size()
    before, limit = held(), spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    dealt, again = graph.deal(e, [12]), graph.deal(e, [12])
    graph.undeal(again)
    assert held() == before + 1  # the first is still there
    sent = cut(spark.createDataFrame([(12, 1), (0, 2), (24, 4), (99, 8)], "v long, m long"))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        got = graph.to_neighbours(sent, dealt)
        assert sorted(tuple(r) for r in got.collect()) == sorted((w, m) for v, m in ((12, 1), (0, 2), (24, 4)) for w in near[v])
        plan = got._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
    assert "SortMergeJoin [src#" in plan  # by the order in which the edges lie
    assert not re.search(r"Exchange hashpartitioning\(src#\d+L?, \d+\), ENSURE_REQUIREMENTS", plan)
    assert sorted(r["id"] for r in graph.dealt_vertices(dealt).collect()) == list(range(25))
    graph.undeal(dealt)
    roots = lmk.explicit(spark, [12, 3])
    gateway.build(e, roots, "sequential"), search_levels.levels_by_masks(e, roots), mask_hybrid.labels(e, roots)
    assert held() == before


def test_failed_build_keeps_no_edges(spark):
    class Stop(list):
        def append(self, x):
            raise InterruptedError

    e, held = edges(spark, GRAPHS["grid5"]), lambda: spark.sparkContext._jsc.getPersistentRDDs().size()
    before = held()
    with pytest.raises(InterruptedError):
        gateway.build(e, lmk.explicit(spark, [12, 3]), trace=Stop())
    assert held() == before
