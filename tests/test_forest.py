"""Main-memory indexes over blocks of a distributed set."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from metricsearch.functions import columns, movement
from metricsearch.functions.metrics import METRICS
from metricsearch.operators import scan, voronoi
from metricsearch.plans import baselines, forest
from metricsearch.plans.baselines import Gnat, Mvpt
from metricsearch.plans.workloads import asked, asked_all
from metricsearch.sources.objects import objects, pick

QUERIES = entry.queries()


@pytest.mark.parametrize("kind", ["gnat", "mvpt", "tree"])
def test_blocks_answer_as_a_scan(spark, small, monkeypatch, kind):
    monkeypatch.setattr(forest, "MOST_ROWS", 70)
    blocks = forest.blocks
    monkeypatch.setattr(forest, "blocks", lambda b, m: blocks(b, m, 70))
    for name, metric, r in (("order_points", "euclid", 90.0), ("doc_words", "jaccard", 0.95), ("part_paths", "sad", 70.0)):
        objs = objects(spark, small, name).persist()
        queries = asked_all(objs, r=r, k=7)
        got = forest.range_search(objs, queries, metric, kind).collect()
        want = scan.range_scan(objs, queries, metric).collect()
        assert want and sorted((x.query_id, x.obj_id, round(x.dist, 9)) for x in got) == sorted((x.query_id, x.obj_id, round(x.dist, 9)) for x in want)
        got = forest.knn(objs, queries, metric, kind).collect()
        want = scan.knn_scan(objs, queries, metric).collect()
        assert want and sorted((x.query_id, x.rank, x.obj_id) for x in got) == sorted((x.query_id, x.rank, x.obj_id) for x in want)


@pytest.mark.parametrize("name", ["knn_part_paths_mvpt", "range_line_words_gnat", "range_order_points_gnat_every100"])
def test_no_set_on_the_driver(spark, small, monkeypatch, name):
    def refuse(*_):
        raise AssertionError("the driver gathers the set")

    monkeypatch.setattr(voronoi, "_gather", refuse)
    assert QUERIES[name](spark, small).count() > 0


def test_equal_distances_do_not_make_a_chain():
    """Sets without common words: every distance is 1, so that no split point is nearer than another."""
    m = METRICS["jaccard"]
    store = m.read(pa.array([[f"w{i}"] for i in range(6000)]))
    made = Gnat(m, store, 4, 20).build()
    assert made.counter.count < 6000 * 60
    found, _ = made.range_search(m.one(store, 17), 0.5)
    assert found == {17: 0.0} and [i for _, i in made.knn(m.one(store, 17), 3)[0]] == [17, 0, 1]


def test_word_sets_read_as_packed():
    m, rows = METRICS["jaccard"], [["b", "a", "b"], [], ["c", "a"], ["d"]]
    for column in (pa.array(rows), pa.array([["x"], *rows]).slice(1)):
        store = m.read(column)
        assert [m.one(store, i) for i in range(4)] == [frozenset(r) for r in rows]
        assert m.many({"a", "z"}, store).tolist() == m.many({"a", "z"}, m.pack(rows)).tolist()


def test_search_within_a_distance():
    m = METRICS["euclid"]
    store = np.random.default_rng(3).random((500, 2))
    for made in (Gnat(m, store, 4, 20).build(), Mvpt(m, store, 4, 20).build()):
        whole, _ = made.knn(store[7], 9)
        assert made.knn(store[7], 9, within=whole[-1][0])[0] == whole
        some, cost = made.knn(store[7], 9, within=whole[3][0])
        assert some[:4] == whole[:4] and cost["total"] < 500


@pytest.mark.parametrize("name", ["cost_by_index", "u_turn_curve", "estimate_comparison", "pruning_ablation"])
def test_costs_are_counted_in_the_tasks(spark, small, monkeypatch, name):
    def refuse(*_):
        raise AssertionError("the driver gathers the set")

    monkeypatch.setattr(voronoi, "_gather", refuse)
    got = QUERIES[name](spark, small).toPandas()
    assert len(got) == {"cost_by_index": 120, "u_turn_curve": 8, "estimate_comparison": 18, "pruning_ablation": 8}[name]
    if name == "cost_by_index":  # the answers of all kinds are the same
        assert (got.groupby(["name", "search", "parameter"]).n_results.nunique() == 1).all()
        scans = got[(got.kind == "scan") & (got.name == "order_points")]
        assert (scans.n_dist == objects(spark, small, "order_points").count()).all()


def test_costs_over_several_blocks(spark, small):
    objs, n = objects(spark, small, "order_points"), []
    queries = asked_all(objs, r=90.0)

    def measure(m, store, queries):
        made = forest.KINDS["tree"](m, store, 8, 20).build()
        return [("tree", float(sum(len(made.range_search(q, 90.0, eager=far)[0]) for q, far in queries)))]

    for parts in (1, 5):
        rows = forest.measured(objs, queries, "euclid", measure, "kind string, n double", parts).collect()
        n.append((len(rows), sum(r.n for r in rows)))
    assert n[0][0] == 1 and n[1][0] == 5 and n[0][1] == n[1][1] == scan.range_scan(objs, queries, "euclid").count()


def _plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_asked_objects_alone_are_made(spark, small):
    """The ids of a query table are a filter of the rows that movements are made of."""
    spark.catalog.clearCache()  # other tests keep the same set
    objs = objects(spark, small, "part_paths")
    queries = asked(objs, 4, r=2.0, k=3)
    ids = sorted(r.obj_id for r in pick(objs, 4).collect())
    assert sorted(r.query_id for r in queries.collect()) == ids and {(r.r, r.k) for r in queries.collect()} == {(2.0, 3)}
    below = _plan(queries).split("Aggregate")[-1]
    assert all(str(i) in below.split("Relation")[0] for i in ids)


def test_asked_as_picked(spark):
    objs = spark.createDataFrame([(i // 2 if i < 30 else None, i) for i in range(33)], "obj_id long, obj long")
    for n in (0, 1, 5, 40):
        want = sorted(str(r.obj_id) for r in pick(objs, n).collect())
        assert sorted(str(r.query_id) for r in asked(objs, n).collect()) == want and len(want) == min(n, 33)


def test_alignment_reads_a_movement_once(spark):
    """No vertex makes the array of all times again, so that the work grows with the vertices, not with their square."""
    t, x = [-7, 3, 4, 90, 1000], [0.0, 1.5, 1.0, 7.0, -2.0]
    rows = spark.createDataFrame([(list(zip(t, x, x)),), ([(5, 2.0, 3.0)],)], "v array<struct<t:bigint,x:double,y:double>>")
    made = rows.select(columns.align(F.col("v")).alias("obj"))
    for got, want in zip(made.collect(), (movement.align(t, x, x), movement.align([5], [2.0], [3.0])), strict=True):
        assert [got.obj[k] for k in ("s", "x", "y")] == [a.tolist() for a in want]
    assert "element_at(transform(" not in _plan(made)


@pytest.mark.parametrize("kind", ["gnat", "mvpt"])
@pytest.mark.parametrize("metric", ["l1", "euclid"])
def test_all_queries_at_once_as_one_by_one(monkeypatch, kind, metric):
    """With many equal objects, queries that are none of them, radii of their own, and few pairs at a time."""
    m, rng = METRICS[metric], np.random.default_rng(5)
    store = np.round(rng.random((900, 2 if metric == "euclid" else 6)) * 40)
    store[300:700] = store[3]
    qs = np.concatenate([store[::9], rng.random((20, store.shape[1])) * 60])
    r = np.where(np.arange(len(qs)) % 5 == 0, 0.0, rng.random(len(qs)) * 30)
    r[7] = np.inf
    made = forest.KINDS[kind](m, store, 8, 20).build()
    want = {(i, j): d for i, q in enumerate(qs) for j, d in made.range_search(q, r[i])[0].items()}
    assert want == {(i, int(j)): d[j] for i, q in enumerate(qs) for d in [m.many(q, store)] for j in np.flatnonzero(d <= r[i])}
    for pairs in (50_000, 7):
        monkeypatch.setattr(baselines, "PAIRS", pairs)
        got = [(int(i), int(j), float(x)) for parts in made.range_search_all(qs, r) for i, j, x in zip(*parts, strict=True)]
        assert len(got) == len(want) and {(i, j): x for i, j, x in got} == want
    assert not list(made.range_search_all(qs[:0], r[:0]))


@pytest.mark.parametrize("kind", ["gnat", "mvpt"])
def test_nodes_are_opened_once_for_all_queries(monkeypatch, kind):
    m, calls = METRICS["l1"], []
    store = np.random.default_rng(4).random((3000, 5))
    made = forest.KINDS[kind](m, store, 8, 20).build()
    for name in ("many", "pairs"):
        monkeypatch.setattr(m, name, lambda *a, f=getattr(m, name): calls.append(1) or f(*a))

    class Sent:
        value = (np.arange(3000), list(store), np.full(3000, 0.2), None)

    found = list(forest._found(made, m, store, [Sent]))
    assert sum(len(at) for _, at, _ in found) >= 3000 and len(calls) < 2000  # fewer than queries


@pytest.mark.parametrize("name", ["letter_hist", "order_points", "embedding_l1"])
def test_searches_of_a_hundredth_as_scans(spark, small, name):
    rows = lambda how: sorted(map(tuple, QUERIES[f"range_{name}_{how}_every100"](spark, small).select("query_id", "obj_id", "dist").collect()))
    want = rows("scan")
    assert want and rows("gnat") == want and rows("mvpt") == want
