"""Worked examples, brute-force references and properties of the engine."""

import math
import random

import numpy as np
import pytest

from pyspark.sql import functions as F

from stagewise import catalogue
from stagewise.functions import hpfunc as H
from stagewise.operators import experiments as X
from stagewise.operators import measures as M
from stagewise.operators import simulate, training, tuners
from stagewise.plans import forest, plan, schedule
from stagewise.plans import trials as T

PIECES = "study string, trial bigint, ord bigint, cfg string, steps bigint"


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def random_pieces(seed, n=25):
    rng = random.Random(seed)
    return [("s", t, k, rng.choice("ab"), rng.choice([0, 5, 10, 15])) for t in range(n) for k in range(rng.randint(1, 4))]


def brute(pieces):
    """(total, unique) by counting distinct histories step by step."""
    total, seen = 0, set()
    by = {}
    for _, t, k, c, n in sorted(pieces):
        by.setdefault(t, []).append((c, n))
    for own in by.values():
        history = ""
        for c, n in own:
            for _ in range(n):
                history += c
                total += 1
                seen.add(history)
    return total, len(seen)


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_merge_rate_equals_step_by_step(spark, seed):
    pieces = random_pieces(seed)
    r = M.merge_rate(T.canonical(spark.createDataFrame(pieces, PIECES))).first()
    assert (r["total_steps"], r["unique_steps"]) == brute(pieces)


def on_tables(spark, d, name):
    """(rows of a query, rows of its SQL over the same tables), both sorted."""
    import duckdb
    from pathlib import Path

    c, df = duckdb.connect(), catalogue.queries()[name](spark, d)
    for f in Path(d).glob("*.parquet"):
        c.execute(f"create view {f.stem} as select * from '{f}{'/*.parquet' if f.is_dir() else ''}'")
    key = lambda r: tuple((x is not None, x) for x in r)
    told = c.execute(f"select {', '.join(chr(34) + x + chr(34) for x in df.columns)} from ({catalogue.oracle_sql()[name]})").fetchall()
    return sorted(map(tuple, df.collect()), key=key), sorted(told, key=key)


def some_orders(spark, rows):
    """A folder whose orders are (orderkey, custkey, status, priority, year) alone."""
    from stagewise.store import Scratch

    d = Scratch(spark, "given").root.removeprefix("file://")
    t = spark.createDataFrame(rows, "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_orderpriority string, y string")
    t.withColumn("o_orderdate", F.concat("y", F.lit("-01-01")).cast("timestamp_ntz")).drop("y").coalesce(1).write.parquet(f"{d}/orders.parquet")
    return d


def test_worked_example_of_four_trials(spark):
    a, b, last = [(0, "0.1")], [(0, "0.1"), (100, "0.05")], [(200, "0.01"), (200, "0.02")]
    expected = [(a, 0, 100, 4), (a, 100, 200, 1), ([*a, last[0]], 200, 300, 1), (b, 100, 200, 3), ([*b, last[0]], 200, 300, 1), ([*b, last[1]], 200, 300, 1), (b, 200, 300, 1)]
    assert rows(forest.merge_trials(catalogue.literal(spark, catalogue._FOUR)).select("path", "lo", "hi", "trials")) == sorted((T.identity(*p), *r) for p, *r in expected)


def test_worked_examples_of_rates(spark):
    fifth = [(5, 0, "0.1", 150), (5, 1, "0.07", 150)]
    assert rows(M.merge_rate(catalogue.literal(spark, catalogue._FOUR + fifth)).drop("nodes")) == [(5, 1500, 850, 1.764706)]
    pairs = [(1, 0, "0.1", 100), (1, 1, "0.01", 100), (2, 0, "0.1", 100), (2, 1, "0.05", 100), (3, 0, "0.01", 100), (3, 1, "0.001", 100), (4, 0, "0.01", 100), (4, 1, "0.005", 100)]
    assert rows(M.merge_rate(catalogue.literal(spark, pairs)).drop("nodes")) == [(4, 800, 600, 1.333333)]


def test_worked_example_of_a_plan(spark):
    n1, n2, n3, n4 = (T.identity(*x) for x in (catalogue._N1, catalogue._N2, catalogue._N3, catalogue._N4))
    tree = [(n1, 10, 15), (n2, 20, 25), (n3, 20, 35), (n3, 35, 40), (n4, 40, 60)]
    own = catalogue.fig_plan(spark)
    assert rows(forest.from_plan(*own).select("path", "lo", "hi")) == sorted(tree)
    assert rows(forest.from_plan(*own, "literal").select("path", "lo", "hi")) == sorted([*tree[:3], (n3, 20, 40), tree[4]])
    held = spark.createDataFrame([(n3, 20, 35)], "path string, lo bigint, hi bigint")
    assert rows(forest.from_plan(*own, running=held).select("path", "lo", "hi", "blocked")) == sorted([(n1, 10, 15, False), (n2, 20, 25, False), (n3, 35, 40, True), (n4, 40, 60, True)])


def test_fig_four_trials_reads_orders(spark, sf):
    got, told = on_tables(spark, sf, "fig_four_trials")
    assert got == told and {r[-1] for r in got} >= {1, 2, 3}
    # customers 4 to 7 are a study, 8 is one of its own
    d = some_orders(spark, [(1, 4, "F", "2", "1992"), (2, 4, "O", "1", "1993"), (3, 5, "F", "2", "1992"), (4, 7, "F", "1", "1992"), (5, 8, "F", "2", "1992")])
    got, told = on_tables(spark, d, "fig_four_trials")
    first, then = T.identity((0, "0.1")), T.identity((0, "0.1"), (100, "0.05"))
    assert got == told == sorted([("1", first, 0, 100, 3), ("1", first, 100, 150, 1), ("1", then, 100, 250, 1), ("2", first, 0, 100, 1)])


def test_fig_fifth_trial_reads_orders(spark, sf):
    got, told = on_tables(spark, sf, "fig_fifth_trial")
    assert got == told and max(r[1] for r in got) == 5
    d = some_orders(spark, [(k, k, "F", "2", "1992") for k in range(4)] + [(9, 4, "F", "1", "1992"), (10, 5, "F", "2", "1992")])
    assert on_tables(spark, d, "fig_fifth_trial") == ([("0", 5, 550, 150, 3.666667), ("1", 1, 100, 100, 1.0)],) * 2


def test_fig_two_pairs_reads_orders(spark, sf):
    got, told = on_tables(spark, sf, "fig_two_pairs")
    assert got == told
    d = some_orders(spark, [(1, 7, "F", "3", "1992"), (2, 7, "F", "2", "1992"), (3, 7, "O", "5", "1992"), (4, 7, "O", "4", "1992"), (5, 8, "F", "1", "1992")])
    assert on_tables(spark, d, "fig_two_pairs") == ([("7", 4, 800, 600, 1.333333), ("8", 1, 200, 200, 1.0)],) * 2


#: The plan of the figure as orders: customers 1 to 4 have its four trials (an order's steps are 10 + 5 (key mod 3)).
PLANNED = [(k, c, "F", p, "1992") for k, c, p in [(1, 1, "1"), (3, 2, "1"), (4, 2, "2"), (2, 3, "1"), (7, 3, "3"), (5, 4, "1"), (8, 4, "3"), (11, 4, "4")]]


def test_fig_plan_tree_reads_orders(spark, sf):
    got, told = on_tables(spark, sf, "fig_plan_tree")
    assert got == told
    n1, n2, n3, n4 = (T.identity(*x) for x in (catalogue._N1, catalogue._N2, catalogue._N3, catalogue._N4))
    assert on_tables(spark, some_orders(spark, PLANNED), "fig_plan_tree") == (sorted([(n1, 10, 15), (n2, 20, 25), (n3, 20, 35), (n3, 35, 40), (n4, 40, 60)]),) * 2


def test_fig_plan_literal_reads_orders(spark, sf):
    got, told = on_tables(spark, sf, "fig_plan_literal")
    assert got == told
    n1, n2, n3, n4 = (T.identity(*x) for x in (catalogue._N1, catalogue._N2, catalogue._N3, catalogue._N4))
    assert on_tables(spark, some_orders(spark, PLANNED), "fig_plan_literal") == (sorted([(n1, 10, 15), (n2, 20, 25), (n3, 20, 35), (n3, 20, 40), (n4, 40, 60)]),) * 2


def test_fig_plan_running_reads_orders(spark, sf):
    got, told = on_tables(spark, sf, "fig_plan_running")
    assert got == told and {r[-1] for r in got} == {True, False}
    n1, n2, n3, n4 = (T.identity(*x) for x in (catalogue._N1, catalogue._N2, catalogue._N3, catalogue._N4))
    assert on_tables(spark, some_orders(spark, PLANNED), "fig_plan_running") == (sorted([(n1, 10, 15, False), (n2, 20, 25, False), (n3, 35, 40, True), (n4, 40, 60, True)]),) * 2


@pytest.mark.parametrize("seed", [4, 5])
def test_insert_equals_merge_of_the_union(spark, seed):
    g = T.canonical(spark.createDataFrame(random_pieces(seed), PIECES))
    a, b = g.where("trial % 3 = 0"), g.where("trial % 3 <> 0")
    key = lambda df: sorted(map(str, rows(df)))
    names = ["path", "lo", "hi", "parent_path", "parent_hi"]
    assert key(forest.insert_trials(forest.merge_trials(a), b).select(names)) == key(forest.merge_trials(g).select(names))


def test_configurations_that_would_read_alike(spark):
    """Slashes and colons in configurations, null and empty ones, and numbers that run into lengths name nodes of their own."""
    p = [("s", 1, 0, "a", 10), ("s", 1, 1, "b", 10), ("s", 2, 0, "a/10:b", 10), ("s", 3, 0, None, 10), ("s", 4, 0, "", 10), ("s", 5, 0, "a", 10), ("s", 5, 1, None, 10), ("s", 6, 0, "-", 10), ("s", 7, 0, "a|10|1:b", 10)]
    g = T.canonical(spark.createDataFrame(p, PIECES))
    assert M.merge_rate(g).first()["unique_steps"] == 80 and T.nodes(g).count() == 8
    got = {r["path"]: (r["lo"], r["hi"], r["parent_path"]) for r in forest.merge_trials(g).collect()}
    a = T.identity((0, "a"))
    assert got == {a: (0, 10, None), T.identity((0, "a"), (10, "b")): (10, 20, a), T.identity((0, "a"), (10, None)): (10, 20, a), **{T.identity((0, c)): (0, 10, None) for c in ("a/10:b", None, "", "-", "a|10|1:b")}}
    assert T.canonical(spark.createDataFrame([("s", 1, 0, None, 5), ("s", 1, 1, None, 5)], PIECES)).count() == 1


def test_identical_trials_and_empty_study(spark):
    p = [("s", t, 0, "a", 10) for t in range(7)]
    assert M.merge_rate(T.canonical(spark.createDataFrame(p, PIECES))).first()["rate"] == 7
    g = T.canonical(spark.createDataFrame([("s", 1, 0, "a", 0)], PIECES))
    assert g.count() == 0 and forest.merge_trials(g).count() == 0 and plan.requests(g).count() == 0


def test_nearest_checkpoint_is_the_climb(spark):
    rng = random.Random(9)
    g = T.canonical(spark.createDataFrame(random_pieces(9), PIECES))
    nodes = {r["path"]: r for r in T.nodes(g).collect()}
    ck = [(p, rng.randint(n["start"], n["reach"])) for p, n in nodes.items() if rng.random() < 0.5]
    ck = [(p, s) for p, s in ck if s > nodes[p]["start"]] or [(next(iter(nodes)), 1)]
    req = plan.requests(g)
    got = {(r["path"], r["step"]): (r["ckpt_path"], r["ckpt_step"]) for r in forest.resume_points(req, spark.createDataFrame(ck, "path string, step bigint"), T.lines(g)).collect()}
    for r in req.collect():
        path, limit, found = r["path"], r["step"], (None, None)
        while path is not None:
            best = [s for p, s in ck if p == path and s <= limit]
            if best:
                found = (path, max(best))
                break
            limit, path = nodes[path]["start"], nodes[path]["parent"]
        assert got[(r["path"], r["step"])] == found
    c = spark.createDataFrame(ck, "path string, step bigint")
    key = lambda df: sorted(map(str, df.select("path", "step", "ckpt_path", "ckpt_step", "up").collect()))
    assert key(forest.climb(req, c, T.nodes(g))) == key(forest.resume_points(req, c, T.lines(g)))


@pytest.mark.parametrize("seed", [11, 12])
def test_chains_are_the_greedy_longest_paths(spark, seed):
    g = T.canonical(spark.createDataFrame(random_pieces(seed), PIECES))
    st = schedule.costs(forest.merge_trials(g))
    table = [r.asDict() for r in st.collect()]
    key = lambda p, h: f"{p}@{h}"
    parent = {key(r["path"], r["hi"]): key(r["parent_path"], r["parent_hi"]) if r["parent_path"] is not None and r["parent_hi"] is not None else None for r in table}
    cost = {key(r["path"], r["hi"]): r["cost"] for r in table}
    left, expected = set(cost), []
    leaves = set(cost) - set(parent.values())
    while left:
        def way(leaf):
            out = []
            while leaf is not None and leaf in left:
                out.append(leaf)
                leaf = parent[leaf]
            return out
        best = max(sorted(leaves & left), key=lambda x: sum(cost[s] for s in way(x)))
        expected.append(sum(cost[s] for s in way(best)))
        left -= set(way(best))
    got = sorted((r["cost"] for r in schedule.chains(st, T.lines(g)).collect()), reverse=True)
    assert got == pytest.approx(sorted(expected, reverse=True))
    names = ["stage", "path", "lo", "hi", "cost", "leaf"]
    assert rows(schedule.elected_by_levels(st).select(names)) == rows(schedule.elected_leaves(st, T.lines(g)).select(names))
    assert rows(schedule.chains(st)) == rows(schedule.chains(st, T.lines(g)))


def test_simulation_of_four_trials():
    stages = [("A", None, "1", 100.0), ("B", "A", "1", 100.0), ("C", "B", "1", 100.0), ("D", "A", "2", 100.0), ("E", "D", "2", 100.0), ("F", "D", "3", 100.0), ("G", "D", "4", 100.0)]
    assert simulate.simulate(stages, 2, "chains")[:2] == (400.0, 700.0)
    assert simulate.simulate(stages, 99, "chains")[0] == 300.0
    for w in (1, 2, 3):
        for policy in ("chains", "breadth"):
            makespan, busy, _ = simulate.simulate(stages, w, policy)
            assert busy == 700 and makespan >= max(300, 700 / w)
    assert simulate.simulate(stages, 2, "breadth")[2] >= simulate.simulate(stages, 2, "chains")[2]


def test_values_by_spark_equal_python(spark, sf):
    for name, pieces in (("restarts", H.cosine_restarts(0.1, 20, 100)), ("warmup", H.warmup(10, 0.1, H.exponential(0.1, 0.9, 90)))):
        expected = [p.value(t) for p in pieces for t in range(p.length)]
        got = [r["value"] for r in catalogue.queries()[f"hp_values_{name}"](spark, sf).orderBy("step").collect()]
        assert got == pytest.approx(expected, abs=1e-8)


def test_hp_values_constant_reads_events(spark, sf):
    got, told = on_tables(spark, sf, "hp_values_constant")
    assert got == told and len(got) == spark.read.parquet(f"{sf}/events.parquet").count() and {r[2] for r in got} == {0.1}


def test_hp_values_cosine_reads_events(spark, sf):
    got, told = on_tables(spark, sf, "hp_values_cosine")
    piece, = H.cosine(0.1, 100, 0.001)
    assert got == told and all(v == pytest.approx(piece.value(t), abs=1e-8) for _, t, v in got) and len({r[1] for r in got}) > 90


def test_hp_values_cyclic_reads_events(spark, sf, tmp_path):
    got, told = on_tables(spark, sf, "hp_values_cyclic")
    expected = [p.value(t) for p in H.cyclic(0.001, 0.1, 10, 100) for t in range(p.length)]
    assert got == told and all(v == pytest.approx(expected[t], abs=1e-8) for _, t, v in got) and len({r[1] for r in got}) > 90
    # reports beyond the setting's end, and without a step
    spark.createDataFrame([(1, '{"k": 100}'), (2, '{"k": -1}'), (3, '{}'), (4, '{"k": 99}')], "event_id bigint, props string").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    got, told = on_tables(spark, str(tmp_path), "hp_values_cyclic")
    assert got == told and [r[2] for r in got] == [None, None, None, 0.0109]


def test_hp_normalise_reads_lineitem(spark, sf):
    got, told = on_tables(spark, sf, "hp_normalise")
    assert got == told and sum(r[2] for r in got) == 3 * spark.read.parquet(f"{sf}/lineitem.parquet").count()
    texts = {r[:2] for r in got}
    assert {("exponential", "constant(0.1)"), ("linear", "constant(0.05)"), ("cosine", "constant(0)")} <= texts and not any(t.startswith("exponential") and t.endswith(",1)") for _, t in texts)


def test_canonical_texts():
    assert H.Piece(5, "exponential", (0.1, 1.0)).text() == H.constant(0.10, 9)[0].text() == "constant(0.1)"
    assert H.step_decay(0.1, 0.1, [50, 200], 100) == H.step_decay(0.1, 0.1, [50], 100)
    (a, b), = [H.cut(H.exponential(0.1, 0.9, 10), {4})]
    assert b[2].value(0) == pytest.approx(0.1 * 0.9**4)


def test_halving_counts_and_async_order():
    assert tuners.rungs(4, 15, 120) == [15, 60, 120]
    assert [(b["trials"], b["first_step"]) for b in tuners.hyperband(4, 8, 32)] == [(4, 8), (2, 32)]
    made = tuners.async_halving([(1, 2, 0.1), (2, 2, 0.9), (3, 2, 0.5), (4, 2, 0.2), (2, 8, 0.9)], 2, [2, 8])
    assert made == [(2, 2), (3, 2)]
    # the same by sorting all results at each report
    rng = random.Random(6)
    reports = [(rng.randrange(40), rng.choice([1, 2, 8, 32]), round(rng.random(), 1)) for _ in range(400)]
    reports = list({(t, s): (t, s, v) for t, s, v in reports}.values())
    for eta in (2, 4):
        done, gone, expected = [[], [], []], [set(), set(), set()], []
        for t, s, v in reports:
            r = {2: 0, 8: 1, 32: 2}.get(s)
            if r is None or r and t not in gone[r - 1]:
                continue
            done[r].append((-v, t))
            for k in (1, 0):
                new = [x for _, x in sorted(done[k])[: len(done[k]) // eta] if x not in gone[k]]
                if new:
                    gone[k].add(new[0])
                    expected.append((new[0], (2, 8)[k]))
                    break
        assert tuners.async_halving(reports, eta, [2, 8, 32]) == expected


def test_halving_of_448(spark):
    m = spark.range(448).selectExpr("'s' as study", "id as trial", "explode(array(15L, 60L, 120L)) as step", "cast(hash(id) as double) as value")
    got = {r["rung"]: r["count"] for r in tuners.halving(m, 4, 15, 120).groupBy("rung").count().collect()}
    assert got == {15: 448, 60: 112, 120: 28}


def test_batches_resume_without_repeats():
    for n in (1, 7, 10, 97):
        seen = np.concatenate([training.rows_at(3, c, 4, n, 5) for c in range(0, n, 4)])
        assert sorted(seen.tolist()) == list(range(n))


def test_batch_slices_reads_events(spark, sf, tmp_path):
    got, told = on_tables(spark, sf, "batch_slices")
    assert got == told and len(got) == spark.read.parquet(f"{sf}/events.parquet").count()
    # batches of 3, 3, 2, 2 rows are those that training takes; keys have gaps
    for n in (0, 1, 2, 7, 10):
        spark.range(n).select((F.col("id") * 7 + 100).alias("event_id")).repartition(4).write.parquet(f"{tmp_path}/{n}/events.parquet")
        expected, at = [], 0
        for batch, size in enumerate([3, 3, 2, 2]):
            expected += [(batch, r, 7 * r + 100) for r in training.rows_at(0, at, size, n, 1).tolist()] if at < n else []
            at += size
        assert on_tables(spark, f"{tmp_path}/{n}", "batch_slices") == (sorted(expected),) * 2


def test_shared_training_is_lossless(spark, sf):
    r = {x["mode"]: x for x in catalogue.queries()["study_grid_cutout"](spark, sf).collect()}
    assert r["trial"]["equal"] and r["stage"]["equal"] and r["stage"]["steps_run"] < r["trial"]["steps_run"]
    assert r["trial"]["best"] == r["stage"]["best"]


@pytest.mark.parametrize("model", [training.Softmax, training.OneHidden])
def test_gradients_equal_differences(model):
    rng = np.random.default_rng(2)
    learner = model(rng.standard_normal((12, 4)), rng.integers(0, 3, 12), 3)
    w, x = rng.standard_normal(learner.fresh().params.shape), learner.with_one(learner.x)

    def loss(w):
        z = x @ w if model is training.Softmax else np.maximum(x @ w[:5], 0) @ w[5:].T
        return float(np.mean(np.log(np.exp(z).sum(axis=1)) - z[np.arange(12), learner.y]))

    g = learner.gradient(x, learner.y, w)
    for at in np.ndindex(*w.shape):
        e = np.zeros_like(w)
        e[at] = 1e-6
        assert abs((loss(w + e) - loss(w - e)) / 2e-6 - g[at]) < 1e-6


def test_costly_transitions_favour_chains(spark, sf):
    r = {(x["study"], x["policy"], x["w"], x["cost"]): x for x in catalogue.queries()["transition_costs"](spark, sf).collect()}
    for (study, policy, w, cost), x in r.items():
        assert x["busy"] >= r[study, policy, w, 0.0]["busy"]
        if policy == "chains":
            assert x["busy"] <= r[study, "breadth", w, cost]["busy"]


def test_halving_that_trains(spark, sf):
    r = {(x["mode"], x["rung"]): x for x in catalogue.queries()["study_sha"](spark, sf).collect()}
    assert [r["trial", k]["trials"] for k in (15, 60, 120)] == [448, 112, 28] == [r["stage", k]["trials"] for k in (15, 60, 120)]
    assert sum(r["trial", k]["steps_run"] for k in (15, 60, 120)) == 13_440
    for k in (15, 60, 120):
        assert r["trial", k]["best"] == r["stage", k]["best"] and r["stage", k]["steps_run"] < r["trial", k]["steps_run"]


def test_checkpoint_round_trip():
    rng = np.random.default_rng(1)
    learner = training.Softmax(rng.standard_normal((20, 5)), rng.integers(0, 3, 20), 3)
    s = learner.fresh()
    for _ in range(7):
        learner.step(s, {"lr": 0.1, "bs": 6, "momentum": -1})
    t = training.State.load(s.dump())
    for x in (s, t):
        learner.step(x, {"lr": 0.1, "bs": 6, "momentum": -1})
    assert s.dump() == t.dump()


def test_pooled_rate_bounds(spark, sf):
    r = {x["k"]: x for x in catalogue.queries()["kwise_high"](spark, sf).collect()}
    for x in r.values():
        assert x["unique"] <= x["within_unique"] <= x["total"]


def test_all_nations_are_costed_and_scheduled(spark, sf):
    import duckdb

    c = duckdb.connect()
    for name in ("orders", "customer"):
        c.sql(f"create view {name} as select * from '{sf}/{name}.parquet'")
    steps = c.sql("select sum(case o_orderstatus when 'F' then 10 when 'O' then 20 else 30 end) from orders").fetchall()[0][0]
    q, sql = catalogue.queries(), catalogue.oracle_sql()
    assert {x["sharing"]: x["unique_steps"] for x in q["merge_unshared"](spark, sf).collect()}["none"] == steps
    work = {}
    for name in ("merge_unshared", "pairwise_rates", "cost_rate", "stage_costs", "critical_path", "chains_orders", "top_chains", "bfs_order", "work_bound"):
        df = q[name](spark, sf)
        expected = c.sql(f"select {', '.join(chr(34) + x + chr(34) for x in df.columns)} from ({sql[name]})").fetchall()
        work[name] = rows(df)
        assert work[name] == sorted(expected), name
    busy = {}
    for x in q["makespan_sweep"](spark, sf).collect():
        busy.setdefault((x["policy"], x["w"]), []).append(x["busy"])
    assert len({tuple(sorted(x)) for x in busy.values()}) == 1 and len(busy["chains", 1]) == 25
    assert sum(busy["chains", 1]) >= work["work_bound"][0][df.columns.index("work")]


def test_metric_steps_hold_every_report(spark, sf):
    import duckdb

    c = duckdb.connect()
    c.sql(f"create view events as select * from '{sf}/events.parquet'")
    got = {r["trial"]: r["values"] for r in catalogue.queries()["metric_steps"](spark, sf).collect()}
    assert got == dict(c.sql(catalogue.oracle_sql()["metric_steps"]).fetchall())
    assert sum(map(len, got.values())) == c.sql("select count(*) from events").fetchall()[0][0]


def test_async_stream_equals_replay(spark, sf):
    from stagewise.streaming import reports

    base = reports.source(spark, f"{sf}/event[s].parquet", spark.read.parquet(f"{sf}/events.parquet").schema)
    shaped = base.select(F.lit("events").alias("study"), F.col("event_id").alias("ord"), F.col("user_id").alias("trial"), (F.col("event_id") % 2 * 6 + 2).alias("step"), "value")
    got = rows(reports.collected(reports.async_promotions(shaped, 4, [2, 8]), "append"))
    t = spark.read.parquet(f"{sf}/events.parquet").select(F.lit("events").alias("study"), F.col("event_id").alias("ord"), F.col("user_id").alias("trial"), (F.col("event_id") % 2 * 6 + 2).alias("step"), "value")
    assert got == rows(tuners.async_replay(t, 4, [2, 8])) and math.isfinite(len(got))


def test_plans_have_no_cartesian_products(spark, sf):
    for name in ("stage_forest", "chains_orders", "nearest_ckpt_asof", "resume_tree_breakpoints", "trials_of_stage"):
        text = catalogue.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in text and "Python" not in text


# --- the loop, studies and experiments ------------------------------------------------------


def small_study(spark, sf, workers=40, **options):
    from stagewise.store import Scratch
    from stagewise.study import Study

    learn, held = catalogue._vectors(spark, sf)
    own = Study.open(spark, "small", training.Softmax, "embeddings", ["lr", "bs"], training.fit_sample(learn), held, 10, root=options.pop("root", None) or Scratch(spark, "plans").root, workers=workers, **options)
    return own, own.trials(catalogue.space.families_small()).persist()


def test_running_stages_are_not_given_out_again(spark):
    """A running stage, what waits for it, and a stage cut where it ends."""
    req, ck, lines = catalogue.fig_plan(spark)
    n1, n3 = T.identity((0, "H1")), T.identity((0, "H1"), (20, "H3"))
    held = spark.createDataFrame([(n3, 20, 30), (n1, 10, 15)], "path string, lo bigint, hi bigint")
    got = {(r["path"], r["lo"], r["hi"]): r["blocked"] for r in forest.from_plan(req, ck, lines, running=held).collect()}
    assert got == {(T.identity((0, "H1"), (10, "H2")), 20, 25): False, (n3, 30, 35): True, (n3, 35, 40): True, (T.identity((0, "H1"), (20, "H3"), (40, "H4")), 40, 60): True}


def test_trees_of_a_plan_know_parents_and_checkpoints(spark):
    req, ck, lines = catalogue.fig_plan(spark)
    n1, n2, n3, n4 = (T.identity(*x) for x in (catalogue._N1, catalogue._N2, catalogue._N3, catalogue._N4))
    got = {(r["path"], r["lo"]): (r["hi"], r["parent_path"], r["parent_hi"], r["resume_path"], r["resume_step"]) for r in forest.from_plan(req, ck, lines).collect()}
    assert got == {
        (n1, 10): (15, None, None, n1, 10), (n2, 20): (25, None, None, n2, 20), (n3, 20): (35, None, None, n1, 20),
        (n3, 35): (40, n3, 35, None, None), (n4, 40): (60, n3, 40, None, None),
    }
    stages = schedule.costs(forest.from_plan(req, ck, lines).withColumn("cfg", F.lit("x")))
    taken = {(r["leaf"], r["path"], r["lo"]) for r in schedule.round(stages, lines, 2).collect()}
    least = min((f"{n1}@15", n1, 10), (f"{n2}@25", n2, 20))  # both cost 5
    assert taken == {(f"{n4}@60", n3, 20), (f"{n4}@60", n3, 35), (f"{n4}@60", n4, 40), least}


def test_plan_store_is_written_once_and_compacted(spark):
    from stagewise.store import PlanStore, Scratch

    store = PlanStore(spark, Scratch(spark, "t").root, "k")
    assert store.read("metrics").count() == 0 and store.parts("metrics") == 0
    rows = spark.createDataFrame([("a", 1, 0.5), ("b", 2, 0.25)], "path string, step bigint, value double")
    for part in ("one", "one", "two"):  # the first part is written twice
        store.append("metrics", rows if part == "one" else rows.withColumn("step", F.col("step") + 5), part)
    assert store.read("metrics").count() == 4 and store.parts("metrics") == 2
    store.compact("metrics")
    assert store.parts("metrics") == 1 and sorted(map(tuple, store.read("metrics").collect())) == [("a", 1, 0.5), ("a", 6, 0.5), ("b", 2, 0.25), ("b", 7, 0.25)]
    assert PlanStore(spark, store.root, "other").read("metrics").count() == 0


def test_reports_are_folded_into_the_plan_once(spark):
    from stagewise.store import PlanStore, Scratch
    from stagewise.streaming import reports

    scratch, woken = Scratch(spark, "t"), []
    told = spark.createDataFrame([("a", 1, 1, 0.1), ("a", 1, 2, 0.2), ("b", 3, 1, 0.3), ("b", 3, 1, 0.3)], "path string, step bigint, ord bigint, value double")
    told.coalesce(1).write.parquet(f"{scratch.root}/in/0")
    told.where("path = 'a'").withColumn("value", F.lit(9.0)).coalesce(1).write.parquet(f"{scratch.root}/in/1")
    store = PlanStore(spark, f"{scratch.root}/plan", "k")
    stream = spark.readStream.schema(told.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{scratch.root}/in")
    assert reports.aggregate(stream, store, woken.append) == 2
    assert sorted(map(tuple, store.read("metrics").collect())) == [("a", 1, 0.2), ("b", 3, 0.3)] and woken == [2]


def test_only_changed_settings_are_passed_on():
    rng = np.random.default_rng(3)
    trainer = training.LearnerTrainer(training.Softmax(rng.standard_normal((20, 5)), rng.integers(0, 3, 20), 3), iteration=3)
    s, last = trainer.fresh(), {}
    last = training.drive(trainer, s, "bs=constant(4);lr=constant(0.5)", 0, 5, last)
    last = training.drive(trainer, s, "bs=constant(8);lr=constant(0.5)", 0, 2, last)
    last = training.drive(trainer, s, "lr=linear(0.5,0,5)", 0, 2, last)
    assert trainer.told == [{"bs": 4.0, "lr": 0.5}, {"bs": 8.0}, {"bs": None}, {"lr": 0.4}]
    assert s.step == 27 and trainer.hp == last == {"lr": 0.4}


def test_studies_of_one_kind_share_a_plan(spark, sf):
    from stagewise.store import Scratch
    from stagewise.study import plan_key

    root = Scratch(spark, "plans").root
    a, g = small_study(spark, sf, root=root, every=8)  # all milestones are multiples of it, so that no step is trained twice
    b, h = small_study(spark, sf, root=root, every=8)
    half = g.where("trial < 8")
    a.engine.submit(half)
    a.engine.run()
    hits, fresh = b.engine.submit(h)
    assert hits == 8 and fresh == 8
    rounds = b.engine.run()
    assert sum(r.steps for r in [*a.engine.rounds, *rounds]) == M.merge_rate(g).first()["unique_steps"]
    assert plan_key("m", "d", ["a", "b"]) == plan_key("m", "d", ["b", "a"]) != plan_key("m", "d", ["a"])


def test_population_forks_the_donors_line(spark):
    from stagewise.study import forked

    g = T.canonical(spark.createDataFrame([("s", 1, 0, "bs=constant(8);lr=constant(0.5)", 30), ("s", 2, 0, "bs=constant(8);lr=constant(0.1)", 30)], PIECES))
    pairs = spark.createDataFrame([("s", 2, 1)], "study string, trial bigint, donor bigint")
    got = forked(g, pairs, 10, "lr", (0.8, 1.2), 1).orderBy("trial", "k").collect()
    assert [(r["trial"], r["start"], r["end"]) for r in got] == [(1, 0, 30), (2, 0, 10), (2, 10, 30)]
    assert got[1]["path"] == got[0]["path"] == got[2]["parent"] and got[2]["cfg"] in ("bs=constant(8);lr=constant(0.4)", "bs=constant(8);lr=constant(0.6)")


def test_asynchronous_halving_on_a_clock():
    """Without sharing and with many workers every trial runs at once; shared prefixes are trained once."""
    alone = {t: [(f"{t}", 0, 10)] for t in range(8)}
    values = {(t, s): t / 10 for t in range(8) for s in (2, 10)}
    makespan, busy, reached, _ = X.simulate_async(alone, values, 4, [2, 10], 99)
    assert makespan == 10 and busy == 8 * 2 + sum(s == 10 for _, s in reached) * 8 and dict(reached)[7] == 10
    shared = {t: [("root", 0, 6), (f"{t}", 6, 10)] for t in range(8)}
    makespan, less, again, _ = X.simulate_async(shared, values, 4, [2, 10], 99)
    assert less == 6 + 4 * sum(s == 10 for _, s in again) and makespan == 10
    assert X.simulate_async(alone, values, 4, [2, 10], 1)[0] == busy


def test_experiments_behave_as_reported(spark, sf):
    """Sharing never costs more; grids save their merge rate, halving more than that, as it explores a part that shares more."""
    rows = {(r["workload"], r["way"]): r for r in catalogue.queries()["table_single"](spark, sf).collect()}
    for (workload, way), r in rows.items():
        other = rows[workload, "trial"]
        assert r["worker_time"] <= other["worker_time"] and r["makespan"] <= rows[workload, "external"]["makespan"]
    for workload, extra in (("grid cutout", 100), ("grid length", 0)):
        trial, stage = rows[workload, "trial"], rows[workload, "stage"]
        assert (trial["worker_time"] - extra) / (stage["worker_time"] - extra) == pytest.approx(stage["rate"], abs=1e-5)
    assert rows["halving", "stage"]["worker_time_speedup"] > rows["halving", "stage"]["rate"]
    assert rows["halving", "stage"]["explored"] > rows["halving", "stage"]["rate"]
    assert rows["halving", "trial"]["worker_time"] == 13_440 + 100
    assert all(r["best"] >= r["target"] for r in rows.values())


def test_grid_work_reads_part(spark, sf, tmp_path):
    got, told = on_tables(spark, sf, "grid_work")
    assert got == told and len({r[0] for r in got}) == 6
    # rates part at steps 10 and 20, batch sizes at 24: 10 + 2 * 14 + 4 * 96 different steps
    parts = [("A/~B", 10, "Brand#1"), ("A/~B", 20, "Brand#2"), ("C", 130, "Brand#25"), ("C", 130, None), ("C", None, "Brand#x"), (None, 1, "Brand#1")]
    spark.createDataFrame(parts, "p_type string, p_size int, p_brand string").coalesce(1).write.parquet(f"{tmp_path}/part.parquet")
    expected = [("A/~B", "external", 580.0), ("A/~B", "stage", 522.0), ("A/~B", "trial", 580.0), ("C", "external", 220.0), ("C", "stage", 220.0), ("C", "trial", 220.0)]
    assert on_tables(spark, str(tmp_path), "grid_work") == (expected, expected)


def test_tuners_of_a_study(spark, sf):
    from stagewise import study

    own, g = small_study(spark, sf, every=8)
    band = own.tune(study.hyperband(2, 16, 64), g).groupBy("bracket").agg(F.countDistinct("trial").alias("n")).collect()
    assert {r["bracket"]: r["n"] for r in band} == {b["bracket"]: b["trials"] for b in tuners.hyperband(2, 16, 64)}
    made = own.tune(study.async_halving(4, 4, 64), g).collect()
    assert len({(r["trial"], r["rung"]) for r in made}) == len(made) and sum(r["rung"] == 4 for r in made) >= 4
    steps = sum(r.steps for r in own.engine.rounds)
    assert own.engine.store.read("ckpts").count() > 0 and steps <= M.merge_rate(g).first()["unique_steps"]
    pbt = own.tune(study.population(32, 64), g).collect()
    assert sum(r["action"] == "fork" for r in pbt) == 3 and sum(r["action"] == "finish" for r in pbt) == 16
