"""Near word sets against brute force."""

import random

import pytest

from metricsearch.operators import set_join


@pytest.mark.parametrize("r", [0.0, 0.2, 0.5])
def test_all_near_sets_meet(spark, r):
    rng, rows = random.Random(4), [(1, []), (2, []), (3, ["a"]), (4, ["b", "a"]), (5, ["a", "b"])]
    words = [f"w{i}" for i in range(60)]
    for i in range(60):
        base = rng.sample(words, rng.randint(1, 25))
        rows += [(10 + 3 * i, base), (11 + 3 * i, rng.sample(base, max(1, len(base) - 2))), (12 + 3 * i, rng.sample(base, len(base)))]
    dist = lambda a, b: 1.0 - len(a & b) / len(a | b) if a | b else 0.0
    sets = [(i, frozenset(w)) for i, w in rows]
    want = sorted((i, j, round(dist(a, b), 9)) for i, a in sets for j, b in sets if i < j and dist(a, b) <= r)
    got = set_join.jaccard_self_join(spark.createDataFrame(rows, "obj_id long, obj array<string>"), r).collect()
    assert sorted((x.s_id, x.t_id, round(x.dist, 9)) for x in got) == want and len(want) > 5


def test_a_word_of_all_sets_does_not_bring_all_together(spark, monkeypatch):
    """Only sets that share a rare word are measured, however frequent another word is."""
    made, write = {}, set_join.scratch.write_table
    monkeypatch.setattr(set_join.scratch, "write_table", lambda df, name, *a, **k: made.setdefault(name, write(df, name, *a, **k)))
    rows = [(i, ["all", *(f"{i}-{j}" for j in range(9))]) for i in range(300)]
    assert set_join.jaccard_self_join(spark.createDataFrame(rows, "obj_id long, obj array<string>"), 0.2).count() == 0
    assert made["near-pairs"].count() == 0


def test_near_sets_meet_in_turns_and_blocks(spark, monkeypatch):
    """Pairs met and measured in many turns, and long lists cut into blocks, give what brute force does."""
    for name, most in (("PAIRS", 2000), ("GATHERED", 20_000), ("BLOCK", 5), ("HELD", 20)):
        monkeypatch.setattr(set_join, name, most)
    rng, sets = random.Random(7), []
    for _ in range(4):
        base = [f"{rng.randrange(10**6)}\"é,{i}" for i in range(30)]
        sets += [frozenset(rng.sample(base, 27)) for _ in range(14)]
    want = sorted((i, j) for i, a in enumerate(sets) for j, b in enumerate(sets) if i < j and 1.0 - len(a & b) / len(a | b) <= 0.15)
    got = set_join.jaccard_self_join(spark.createDataFrame([(i, list(a)) for i, a in enumerate(sets)], "obj_id long, obj array<string>"), 0.15).collect()
    assert sorted((x.s_id, x.t_id) for x in got) == want and 50 < len(want) < 364


def test_few_shared_rare_words_do_not_make_a_pair(spark, monkeypatch):
    """Each two sets share a rare word, and near ones must share many: none is measured, whose sets would fill the disk."""
    made, write = {}, set_join.scratch.write_table
    monkeypatch.setattr(set_join.scratch, "write_table", lambda df, name, *a, **k: made.setdefault(name, write(df, name, *a, **k)))
    rows = [(i, [f"{min(i, j)}-{max(i, j)}" for j in range(40) if j != i] + [f"own-{i}-{j}" for j in range(161)]) for i in range(40)]
    monkeypatch.setattr(set_join, "RANKED", 0)  # the shared words come first by name
    assert set_join.jaccard_self_join(spark.createDataFrame(rows, "obj_id long, obj array<string>"), 0.2).count() == 0
    assert made["near-pairs"].count() == 0
