"""Registered queries against DuckDB on the smallest tables, and operators of the distributed side."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from metricsearch.operators import filter_refine, scan, voronoi
from metricsearch.plans import index as ix
from metricsearch.plans.workloads import asked, distance_histogram_whole, spread_pairs
from metricsearch.sources.objects import SETS, objects, pick
from metricsearch.sources.tables import sink_noop

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES = entry.queries()
ORACLES = entry.oracle_sql()
OWN = [n for n in QUERIES if not (n.startswith("op") and n[2:3].isdigit()) and n != "pipeline"]
PICKED = [n for n in OWN if n in ORACLES and not (n.startswith(("range_", "knn_")) and n.endswith(("gnat", "mvpt"))) and not n.startswith("op_")]
PICKED += ["op_join_asof", "op_join_range", "op_lateral_topk", "op_cube", "op_json_k", "op_udaf", "op_udtf", "op_udf_arrow", "op_cte_recursive", "op_partitioned_overwrite", "range_order_points_gnat", "knn_part_paths_mvpt", "knn_part_paths_gnat"]


@pytest.fixture(scope="session")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    return con


def rows(df):
    df = df[sorted(df.columns)]
    return sorted(tuple(str(round(float(x), 5)) if isinstance(x, (float, np.floating)) else str(x) for x in r) for r in df.itertuples(index=False))


@pytest.mark.parametrize("name", PICKED)
def test_twin(spark, duck, small, name):
    got = QUERIES[name](spark, small).toPandas()
    want = duck.execute(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_searches_grow_with_the_set(spark, small):
    for name in ("order_points", "doc_words", "part_paths", "letter_hist"):
        objs = objects(spark, small, name)
        want = sorted(r.obj_id for r in objs.where("obj_id % 100 = 0").select("obj_id").collect())
        got = QUERIES[f"knn_{name}_tree_every100"](spark, small).select("query_id").distinct().collect()
        assert want and sorted(r.query_id for r in got) == want


@pytest.mark.parametrize("name", ["op_roundtrip_csv_whole", "op_unpivot_whole", "op_udtf_whole"])
def test_whole_tables(spark, duck, small, name):
    test_twin(spark, duck, small, name)


@pytest.mark.parametrize("name", ["range_join_orders_whole", "range_join_orders_tree_whole"])
def test_whole_join(spark, small, name):
    p = objects(spark, small, "order_points").select("obj_id", "obj.x", "obj.y").toPandas()
    dist = np.hypot(p.x.to_numpy()[:, None] - p.x.to_numpy(), p.y.to_numpy()[:, None] - p.y.to_numpy())
    i, j = np.nonzero(dist <= 12.0000137)
    ids = p.obj_id.to_numpy()
    assert sorted((r.s_id, r.t_id) for r in QUERIES[name](spark, small).collect()) == sorted(zip(ids[i].tolist(), ids[j].tolist()))


def test_histogram_of_all_objects(spark, small):
    objs = objects(spark, small, "order_points")
    n = objs.count()
    for most in (500_000, 2 * n + 7, n // 2):
        pairs = [tuple(sorted((r.a_id, r.b_id))) for r in spread_pairs(objs, most).collect()]
        assert len(pairs) == len(set(pairs)) == most and all(a < b for a, b in pairs)
        assert most < n or len({x for p in pairs for x in p}) == n
    few = objs.limit(40).persist()
    assert spread_pairs(few).count() == 780
    p = few.select("obj_id", "obj.x", "obj.y").toPandas()
    d = np.hypot(p.x.to_numpy()[:, None] - p.x.to_numpy(), p.y.to_numpy()[:, None] - p.y.to_numpy())[np.triu_indices(40, 1)]
    bins, count = np.unique(np.floor(np.round(d, 9) / 100.0), return_counts=True)
    assert sorted((r.bin, r.n) for r in distance_histogram_whole(few, "euclid", 100.0).collect()) == list(zip(bins.astype(int).tolist(), count.tolist()))


def test_entry_and_registry(spark, small):
    assert entry.entry(spark).count() > 0
    assert set(ORACLES) <= set(QUERIES)


@pytest.fixture(scope="session")
def paths(spark, small):
    return objects(spark, small, "part_paths").persist()


def test_index_roundtrip_costs_and_subtrees(spark, paths, tmp_path):
    tree = ix.build(paths, "sad", 4, 8, levels=2)
    queries = asked(paths, r=60.0, k=5)
    want = sorted((r.query_id, r.obj_id) for r in scan.range_scan(paths, queries, "sad").collect())
    for measure in (True, False):
        found = ix.range_search(tree, queries, measure=measure)
        assert sorted((r.query_id, r.obj_id) for r in ix.results(found).collect()) == want
    assert ix.costs(found).agg(F.min("n_dist")).first()[0] > 0
    ix.save_index(tree, str(tmp_path / "i"))
    again = ix.load_index(spark, str(tmp_path / "i"))
    assert sorted((r.query_id, r.obj_id) for r in ix.results(ix.range_search(again, queries)).collect()) == want
    rel = ix.relations(again)
    assert set(rel) == {"nodes", "distances", "pivots", "info"} and rel["distances"].where("e1 >= e2").isEmpty()
    inner = again.nodes.where("subtree is not null").select("subtree").first()
    if inner:
        assert ix.subtree(again, inner[0]).count() > 0
    from metricsearch.sources import index_source

    index_source.register(spark)
    got = spark.read.format("metric_index").load(str(tmp_path / "i"))
    assert got.count() == paths.count()
    part = got.first()["part"]
    assert got.where(F.col("part") == part).count() == ix.members_table(again).where(F.col("part") == part).count()


def test_large_parts_are_split_again(spark, paths):
    tree = ix.build(paths, "sad", 4, 8, part_rows=20)
    assert max(tree.sizes.values()) <= 20 and sum(tree.sizes.values()) == paths.count()


def test_empty_set_and_nulls(spark):
    none = spark.createDataFrame([], "obj_id long, obj struct<x:double,y:double>")
    tree = ix.build(none, "euclid", 4, 8)
    queries = spark.createDataFrame([(1, (0.0, 0.0), 5.0, 3)], "query_id long, obj struct<x:double,y:double>, r double, k int")
    assert ix.results(ix.range_search(tree, queries)).count() == 0
    assert scan.range_scan(none, queries, "euclid").count() == 0 and scan.knn_scan(none, queries, "euclid").count() == 0
    some = spark.createDataFrame([(1, (0.0, 0.0)), (None, (1.0, 1.0)), (2, None), (3, (3.0, 4.0))], none.schema)
    assert sorted(r.obj_id for r in ix.results(ix.range_search(ix.build(some, "euclid", 4, 8), queries)).collect()) == [1, 3]


def test_filter_refine_identity(spark, paths):
    tubed = filter_refine.attach_tubes(paths, 10.0).persist()
    queries, results = asked(paths, r=60.0), set()
    for bounds in ("max", "mean", "own"):
        s = filter_refine.filter_stats(tubed, queries, 10.0, bounds, use_hull=False).first()
        assert s.n_exact == s.n_filter - s.n_accepted
        results.add(s.n_result)
    assert results == {scan.range_scan(paths, queries, "sad").count()}


def test_salted_keys_meet(spark, paths):
    centers = voronoi.pick_centers(paths, "sad", 6)
    placed = voronoi.salt(voronoi.assign(paths, centers), 20)
    copies = voronoi.copy_for_salts(spark.range(6).selectExpr("cast(id as int) as cell"), 20)
    assert placed.join(copies, ["cell", "salted"]).count() == paths.count()


def test_query_blocks(spark, paths):
    queries = asked(paths, 30)
    blocks = scan.query_blocks(queries, 8)
    assert len(blocks) > 1 and sum(b.count() for b in blocks) == 30


def test_sets_are_there(spark, small):
    for name in SETS:
        df = objects(spark, small, name)
        assert df.columns == ["obj_id", "obj"] and pick(df, 3).count() == 3
    sink_noop(df)


def test_filter_reaches_the_scan(spark, small):
    plan = QUERIES["op_scan_pruned"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate), GreaterThanOrEqual(l_shipdate" in plan and "l_discount" not in plan


def test_filter_grid_moves_as_tubes_grow(spark, small):
    """Results stay, the filter keeps more, fewer are accepted, and more are measured, the wider the tubes."""
    got = QUERIES["fr_grid_counts"](spark, small).toPandas().sort_values(["r", "tube_radius"])
    assert len(got) == 16 and (got.n_exact == got.n_filter - got.n_accepted).all()
    for _, part in got.groupby("r"):
        assert part.n_result.nunique() == 1
        assert part.n_filter.is_monotonic_increasing and part.n_accepted.is_monotonic_decreasing and part.n_exact.is_monotonic_increasing


def test_filter_and_refine_in_blocks(spark, small, monkeypatch):
    paths = objects(spark, small, "part_paths")
    tubed = filter_refine.attach_tubes(paths, 10.0).persist()
    queries = asked(paths, n=9, r=55.0)
    whole = sorted(filter_refine.range_filter_refine(tubed, queries, 10.0).select("query_id", "obj_id").collect())
    blocks = scan.query_blocks
    monkeypatch.setattr(filter_refine, "query_blocks", lambda q: blocks(q, 4))
    assert sorted(filter_refine.range_filter_refine(tubed, queries, 10.0).select("query_id", "obj_id").collect()) == whole
    assert whole == sorted(scan.range_scan(paths, queries, "sad").select("query_id", "obj_id").collect())


def test_verdicts_of_an_object_go_together(spark, small, monkeypatch):
    """An object is fetched once for all queries and radii that leave it undecided, and counts are those of pairs."""
    made, write = {}, filter_refine.scratch.write_table
    monkeypatch.setattr(filter_refine.scratch, "write_table", lambda df, name, *a, **k: made.setdefault(name, write(df, name, *a, **k)))
    paths = objects(spark, small, "part_paths")
    tubed = filter_refine.attach_tubes(paths, 20.0).persist()
    queries = asked(paths, n=6, r=45.0).unionByName(asked(paths, n=6, r=120.0))
    got = {x.r: x for x in filter_refine.filter_stats(tubed, queries, 20.0, "own", by_radius=True).collect()}
    assert made["judged"].count() <= paths.count() < sum(x.n_filter for x in got.values())
    for r in (45.0, 120.0):
        assert got[r].n_result == scan.range_scan(paths, asked(paths, n=6, r=r), "sad").count()
    monkeypatch.setattr(filter_refine, "HELD", 7)
    made.clear()
    assert {x.r: x for x in filter_refine.filter_stats(tubed, queries, 20.0, "own", by_radius=True).collect()} == got


def test_a_distance_is_taken_once_for_all_radii(monkeypatch):
    import types

    import pyarrow as pa

    from metricsearch.functions import movement

    paths = [movement.align([0, 1, 3], [0.0, i, 2.0], [0.0, 1.0, i]) for i in range(4)]
    sad, measured = filter_refine.METRICS["sad"], []
    monkeypatch.setattr(type(sad), "many", lambda self, q, store, index: measured.extend(index) or movement.sad_many(q, movement.pick(store, index)))
    asks = [[{"query_id": q, "r": r, "code": 2} for r in (1.0, 2.0, 3.0) for q in (9, 8)], [], [{"query_id": 9, "r": 2.0, "code": 2}]]
    batch = pa.RecordBatch.from_pylist([{"obj_id": 10 * i, "asks": a, "obj": dict(zip("sxy", (c.tolist() for c in paths[i]), strict=True))} for i, a in enumerate(asks)])
    (out,) = filter_refine._measure(types.SimpleNamespace(value={8: paths[3], 9: paths[1]}))([batch])
    assert len(measured) == 3
    assert [(x["query_id"], x["obj_id"], x["r"]) for x in out.to_pylist()] == [(a["query_id"], 10 * i, a["r"]) for i, row in enumerate(asks) for a in row]
    assert out["dist"].to_pylist() == pytest.approx([movement.sad(paths[3 if x["query_id"] == 8 else 1], paths[x["obj_id"] // 10]) for x in out.to_pylist()])


def test_packed_ids_never_meet(spark):
    from metricsearch.sources.objects import packed

    df = spark.createDataFrame([(1, 0), (1, 99), (2, 0)], "a long, b long").select(packed(F.col("a"), F.col("b"), 100).alias("id"))
    assert [r.id for r in df.collect()] == [100, 199, 200]
    for bad in (100, -1):
        with pytest.raises(Exception, match="an id part outside 0 to 99"):
            spark.createDataFrame([(1, bad)], "a long, b long").select(packed(F.col("a"), F.col("b"), 100).alias("id")).collect()


def test_pairwise_measures_each_row(spark, small):
    from metricsearch.functions import movement
    from metricsearch.functions.register import pairwise

    m = objects(spark, small, "week_paths")
    both = pick(m, 4).select(F.col("obj").alias("a")).join(pick(m, 6, 2).select(F.col("obj").alias("b")))
    for r in both.select("a", "b", pairwise("sad")("a", "b").alias("d"), pairwise("hausdorff")("a", "b").alias("h")).collect():
        u, v = (tuple(np.array(x[k]) for k in ("s", "x", "y")) for x in (r.a, r.b))
        assert r.d == pytest.approx(movement.sad(u, v)) and r.h == pytest.approx(movement.hausdorff_many(u, movement.flatten([v]))[0])


def test_recursion_reads_the_customers(spark, small):
    got = QUERIES["op_cte_recursive"](spark, small)
    assert sorted(r.node for r in got.collect()) == sorted(r.c_custkey for r in spark.read.parquet(f"{small}/customer.parquet").select("c_custkey").collect())
    assert got.inputFiles() or "customer" in got._jdf.queryExecution().toString()


def test_filter_grid_counts_copies(spark, small, monkeypatch):
    """Equal movements are judged once, and counted as often as they are there, asked ones too."""
    from metricsearch.plans import workloads

    paths = objects(spark, small, "part_paths").where("obj_id < 120").persist()
    n = paths.count()
    both = paths.unionByName(paths.select((F.col("obj_id") + 1000).alias("obj_id"), "obj")).persist()
    judged = []
    attach = filter_refine.attach_tubes
    monkeypatch.setattr(filter_refine, "attach_tubes", lambda o, r: judged.append(o.count()) or attach(o, r))
    one = workloads.filter_grid(paths, (10.0,), (60.0, 250.0)).toPandas().sort_values("r")
    two = workloads.filter_grid(both, (10.0,), (60.0, 250.0)).toPandas().sort_values("r")
    assert judged == [n, n] and (one.n_result > 0).all()
    for c in ("n_filter", "n_accepted", "n_exact", "n_result"):
        assert (two[c].to_numpy() == 4 * one[c].to_numpy()).all()
    want = scan.range_scan(both, workloads.asked_all(both, r=60.0), "sad").count()
    assert two.n_result.iloc[0] == want
