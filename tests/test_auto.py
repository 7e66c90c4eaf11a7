"""The choice of a strategy, and that every choice gives the same answers."""

from metricsearch.operators.scan import knn_scan, range_scan
from metricsearch.plans import auto
from metricsearch.plans.workloads import asked
from metricsearch.sources.objects import objects


def test_choice_and_answers(spark, small):
    assert auto.choose_strategy(objects(spark, small, "embedding_l1"), "l1") == "scan"
    assert auto.choose_strategy(objects(spark, small, "order_points"), "euclid") == "scan"
    paths = objects(spark, small, "part_paths").persist()
    assert auto.choose_strategy(paths, "sad") == "tubes"
    queries = asked(paths, r=55.0, k=4)
    want = sorted((r.query_id, r.obj_id) for r in range_scan(paths, queries, "sad").collect())
    assert sorted((r.query_id, r.obj_id) for r in auto.search(paths, queries, "sad").collect()) == want
    best = sorted((r.query_id, r["rank"], r.obj_id) for r in knn_scan(paths, queries, "sad").collect())
    assert sorted((r.query_id, r["rank"], r.obj_id) for r in auto.search(paths, queries, "sad", knn=True, k=4, leaf=8).collect()) == best


def test_one_form_of_results(spark, small):
    """The same rows and distances, whatever the strategy."""
    paths = objects(spark, small, "part_paths").persist()
    queries = asked(paths, r=55.0)
    found = {how: auto.search(paths, queries, "sad", strategy=how) for how in ("scan", "tubes", "tree")}
    shown = {how: sorted((r.query_id, r.obj_id, round(r.dist, 6)) for r in df.collect()) for how, df in found.items()}
    assert shown["scan"] == shown["tubes"] == shown["tree"] and shown["scan"]
    assert len({tuple(df.columns) for df in found.values()}) == 1
