"""Worked examples, invariants of the bounds, and equality of all strategies."""

import pytest
from pyspark.sql import functions as F

from chronopath import measures
from chronopath.functions.algebra import ALGEBRAS, LIKELIEST, NARROWEST, SHORTEST, WIDEST
from chronopath.functions.masks import chosen_words, expand, mask_of
from chronopath.plans import bounds as B
from chronopath.plans import concurrent as C
from chronopath.plans import evolve as E
from chronopath.plans import incremental, planner, sharing
from chronopath.plans import residual as R
from chronopath.plans import strategies as S
from chronopath.plans.fixpoint import Work, solve_full

from reference import LIFETIMES, NAMES, everywhere, four_snapshots, random_lives, solve, two_snapshots


def lives(spark, rows):
    return spark.createDataFrame(rows, LIFETIMES).cache()


def answer(df):
    return {(r.v, r.snap): r.val for r in df.collect()}


def prepared(spark, rows, algebra, n):
    query = S.PathQuery(0, algebra, tuple(range(n)))
    return S.prepare(lives(spark, rows), query, S.RunStats("test", algebra.name))


def test_two_snapshot_example(spark):
    p = prepared(spark, two_snapshots(), SHORTEST, 2)
    name = {i: c for c, i in NAMES.items()}
    found = {name[r.v]: (r.core_val, r.hull_val) for r in p.bound.collect()}
    assert found == {"s": (0, 0), "a": (3, 3), "b": (4, 4), "x": (1, 1), "r": (2, 2), "c": (11, 9), "d": (3, 2), "p": (5, 4), "q": (6, 5), "y": (8, 5)}
    edges = lambda df: {name[r.src] + name[r.dst] for r in df.collect()}
    assert edges(p.residual) == {"sd", "ac", "dp", "pq", "py"}
    assert edges(R.residual_by_removal(p.core, B.stable_vertices(p.bound))) == edges(p.residual)
    assert edges(E.addition_set(p.trimmed, 0)) == {"xd", "bc"} and edges(E.addition_set(p.trimmed, 1)) == {"dc", "sy"}
    assert edges(R.loop_edges(C.versioned_graph(p.residual, p.trimmed, range(2)), p.unstable)) == {"dp", "pq", "py", "dc"}
    results = S.run("residual_conc", lives(spark, two_snapshots()), S.PathQuery(0, SHORTEST, (0, 1)))[0]
    row = measures.detection(p.bound, results, 2).first()
    assert (row.stable, row.unchanged, row.unsafe) == (5, 6, 0)
    assert [name[r.v] for r in B.missed_unchanged(p.bound, results, 2).collect()] == ["c"]


@pytest.mark.parametrize("frontier", ["private", "shared"])
def test_four_snapshot_masks(spark, frontier):
    p = prepared(spark, four_snapshots(), SHORTEST, 4)
    assert {r.v for r in B.stable_vertices(p.bound).collect()} == {0, 1}
    loop, work = R.loop_edges(C.versioned_graph(p.residual, p.trimmed, range(4)), p.unstable), Work()
    start, settled = p.core_state.join(p.unstable, "v", "left_semi"), p.core_state.join(p.unstable, "v", "left_anti")
    state = C.solve_concurrent(C.everywhere(settled, range(4)), C.everywhere(start, range(4)), p.trimmed, loop, SHORTEST, frontier, work)
    assert {(r.v, r.val, r.mask) for r in state.collect()} == {(2, 3, 3), (2, 5, 12), (3, 4, 3), (3, 6, 12), (4, 5, 1), (4, 7, 4)}


def test_core_and_redundant_additions(spark):
    k1, k2, p, q, r, t = ((i, i + 10, 1.0) for i in range(6))
    sets = [[k1, k2, p, q], [k1, k2, q, r], [k1, k2, r, t]]
    rows = [(*e, i, i + 1) for i, s in enumerate(sets) for e in s]
    bits = E.classified(lives(spark, rows), range(3), SHORTEST)
    assert {x.src for x in E.core_graph(bits).collect()} == {0, 1}
    adds = E.addition_sets(bits, SHORTEST)
    assert adds.agg(F.sum(F.bit_count("mask"))).first()[0] == 6 and adds.count() == 4
    tree = sharing.plan_tree(0, 2)
    merged = {(0, 3): 2, (0, 1): 1, (0, 2): 1, (1, 3): 1, (2, 3): 1}
    assert sum(n for *_, n in sharing.tree_sizes(merged, tree)[1:]) == 5
    assert sum(n for *_, n in sharing.tree_sizes(merged, sharing.plan_tree(0, 2, merged))[1:]) == 5


def test_deletion_with_tied_cycle(spark):
    edges = spark.createDataFrame([(0, 1, 3.0), (1, 2, 7.0), (2, 1, 7.0)], "src long, dst long, w double")
    state = solve_full(edges, 0, WIDEST, track_parent=True)
    gone = edges.where("src = 0").select("src", "dst")
    left = incremental.apply_deletions(state, edges.where("src <> 0"), gone, WIDEST)
    assert [r.v for r in left.collect()] == [0]


@pytest.mark.parametrize("algebra,core,hull,added", [(SHORTEST, 9.0, 4.0, {0, 1}), (WIDEST, 4.0, 9.0, {2, 3, 4})])
def test_weight_that_changes(spark, algebra, core, hull, added):
    df = lives(spark, [(0, 1, 4.0, 0, 2), (0, 1, 9.0, 3, 5), (2, 3, 4.0, 0, 2), (2, 3, 9.0, 2, 5)])
    rows = E.classified(df, range(5), algebra)
    assert [(r.src, r.w) for r in E.core_graph(rows).collect()] == [(2, core)]
    assert {(r.src, r.w) for r in E.hull_graph(rows).collect()} == {(0, hull), (2, hull)}
    own = E.addition_sets(rows, algebra).where("src = 2").collect()
    assert {i for r in own for i in range(5) if r.mask >> i & 1} == added
    assert E.core_graph(E.classified(df, range(5), algebra, "triple")).count() == 0


@pytest.mark.parametrize("name", list(ALGEBRAS))
def test_bounds_enclose_and_settle_safely(spark, name):
    rows, algebra = random_lives(5), ALGEBRAS[name]
    p, truth = prepared(spark, rows, algebra, 4), everywhere(rows, range(4), 0, algebra)
    bound = {r.v: r for r in p.bound.collect()}
    for (v, _), value in truth.items():
        low, high = bound[v].lower, bound[v].upper
        assert (low is None or low <= value) and (high is None or value <= high)
    for v, r in bound.items():
        if r.core_val == r.hull_val:
            assert all(truth.get((v, i)) == r.core_val for i in range(4))


@pytest.mark.parametrize("name,strategies", [("shortest", tuple(S.STRATEGIES)), ("widest", ("residual_conc", "residual_conc_shared", "stream_inc", "residual_share")), ("hops", ("residual_conc", "stream_inc")), ("narrowest", ("residual_conc", "core_share")), ("likeliest", ("residual_conc", "residual_seq"))])
def test_strategies_agree(spark, name, strategies):
    rows, algebra = random_lives(7, vertices=12, snapshots=3), ALGEBRAS[name]
    truth = everywhere(rows, range(3), 0, algebra)
    for s in strategies:
        assert answer(S.run(s, lives(spark, rows), S.PathQuery(0, algebra, (0, 1, 2)))[0]) == truth, s


def test_chosen_snapshots_with_gaps_and_auto(spark):
    rows = random_lives(11, vertices=12, snapshots=6)
    truth = everywhere(rows, (0, 2, 5), 0, SHORTEST)
    assert answer(S.run("auto", lives(spark, rows), S.PathQuery(0, SHORTEST, (0, 2, 5)))[0]) == truth
    with pytest.raises(ValueError):
        S.run("core_share", lives(spark, rows), S.PathQuery(0, SHORTEST, (0, 2, 5)))


@pytest.mark.parametrize("snapshots", [64, 130])
def test_many_snapshots(spark, snapshots):
    rows = [(0, 1, 2.0, 0, snapshots), (1, 2, 1.0, 0, snapshots), (0, 2, 1.0, snapshots - 1, snapshots), (2, 3, 1.0, 0, snapshots - 1)]
    got = answer(S.run("residual_conc", lives(spark, rows), S.PathQuery(0, SHORTEST, tuple(range(snapshots))))[0])
    assert got == everywhere(rows, range(snapshots), 0, SHORTEST)


def test_edge_cases(spark):
    rows = [(0, 1, 0.0, 0, 2), (1, 2, 0.0, 0, 2), (5, 6, 1.0, 0, 1)]
    df = lives(spark, rows)
    assert answer(S.run("residual_conc", df, S.PathQuery(0, SHORTEST, (0,)))[0]) == everywhere(rows, (0,), 0, SHORTEST)
    assert answer(S.run("residual_conc", df, S.PathQuery(77, SHORTEST, (0, 1)))[0]) == {(77, 0): 0.0, (77, 1): 0.0}
    only_added = [(0, 1, 3.0, 1, 2), (1, 2, 1.0, 0, 2)]
    assert answer(S.run("residual_conc", lives(spark, only_added), S.PathQuery(0, SHORTEST, (0, 1)))[0]) == everywhere(only_added, (0, 1), 0, SHORTEST)
    empty = lives(spark, [])
    assert answer(S.run("residual_conc", empty, S.PathQuery(0, SHORTEST, (0, 1)))[0]) == {(0, 0): 0.0, (0, 1): 0.0}


def test_frozen_grow_and_shrink(spark):
    edges = spark.createDataFrame([(i, j, float(1 + (i + j) % 5)) for i in range(8) for j in range(8) if i != j], "src long, dst long, w double")
    frozen = E.classified(E.frozen(edges, 3), range(3), SHORTEST)
    assert E.addition_sets(frozen, SHORTEST).count() == 0 and E.core_graph(frozen).count() == 56
    for kind, at in ((E.grow_only, 0), (E.shrink_only, 2)):
        lt = kind(edges, 3, 4)
        assert sorted(E.core_graph(E.classified(lt, range(3), SHORTEST)).collect()) == sorted(E.snapshot(lt, at).collect())


def test_script_and_batches(spark):
    edges = spark.createDataFrame([(i, j, 1.0) for i in range(10) for j in range(10) if i != j], "src long, dst long, w double")
    lt = E.scripted(edges, 5, 6).cache()
    sizes = {(r.step, r.op): r.n for r in E.batches(lt, 5).groupBy("step", "op").agg(F.count("*").alias("n")).collect()}
    assert sizes == {(i, op): 3 for i in range(1, 5) for op in ("add", "del")}
    back = E.lifetimes_from_batches(E.snapshot(lt, 0), E.batches(lt, 5), 5)
    assert sorted(back.select(lt.columns).collect()) == sorted(lt.collect())
    flap = E.flapping(edges, 6, 6).groupBy("src", "dst").agg(F.count("*").alias("n")).where("n > 1")
    assert flap.count() > 0


def test_sliding_merges_lives(spark):
    timed = spark.createDataFrame([(0, 1, 5.0, 3), (0, 1, 4.0, 5), (0, 1, 9.0, 20)], "src long, dst long, w double, at int")
    lt = E.sliding(timed, 3, 1, 24)
    alive = {i for r in lt.collect() for i in range(r.born, r.died)}
    assert alive == {i for at in (3, 5, 20) for i in range(24) if i <= at < i + 3} and lt.count() == 2


def test_masks(spark):
    pairs = [(b, d) for b in range(0, 131, 13) for d in range(b, 131, 7)]
    df = spark.createDataFrame(pairs, "born int, died int").join(spark.createDataFrame([(0,), (1,), (2,)], "word int"))
    got = {}
    for r in expand(df.withColumn("mask", mask_of())).collect():
        got.setdefault((r.born, r.died), set()).add(r.snap)
    assert got == {(b, d): set(range(b, d)) for b, d in pairs if d > b}
    assert chosen_words([0, 63, 64]) == {0: 1 - (1 << 63), 1: 1}


@pytest.mark.parametrize("algebra,w", [(SHORTEST, -1.0), (LIKELIEST, 0.5), (NARROWEST, -2.0), (WIDEST, 0.0)])
def test_contracts(spark, algebra, w):
    bad = spark.createDataFrame([(0, 1, w)], "src long, dst long, w double")
    with pytest.raises(Exception, match="weights must satisfy"):
        algebra.checked(bad).collect()


def test_planner():
    assert [s.name for s in planner.schedule((2, 0, 1), "residual_conc")] == ["core", "hull", "reduce", "concurrent"]
    assert len(planner.schedule(range(4), "stream_inc")) == 4 and planner.reusable(range(8), (2, 3))
    assert planner.choose(planner.Counts(10, 5, 100, 90, 4)) == "core_conc" and planner.residual_mode(1, 10) == "semi"
    assert planner.traversal(9, 10) == "pull" and planner.traversal(1, 10) == "push"


def test_optimal_tree_is_never_worse():
    counts = {(0, 4): 5, (3, 4): 9, (0, 1): 2, (2, 4): 1, (1, 3): 4}
    total = lambda tree: sum(n for *_, n in sharing.tree_sizes(counts, tree)[1:])
    assert total(sharing.plan_tree(0, 3, counts)) <= total(sharing.plan_tree(0, 3))


def test_fused_batches_and_tree_of_bounds(spark):
    rows = random_lives(13, vertices=12, snapshots=3)
    query, df = S.PathQuery(0, SHORTEST, (0, 1, 2)), lives(spark, rows)
    assert answer(S.stream_inc(df, query, S.RunStats("stream_inc", "shortest"), fused=True)) == everywhere(rows, range(3), 0, SHORTEST)
    parts = dict(B.bounds_tree(df, [0, 1, 2], 0, SHORTEST, 1))
    whole = {r.v for r in B.stable_vertices(parts[0, 2]).collect()}
    assert whole <= {r.v for r in B.stable_vertices(parts[1, 2]).collect()} | ({r.v for r in parts[0, 2].collect()} - set(solve(rows, 1, 0, SHORTEST)))


def test_round_plan_stays_in_the_jvm(spark):
    state = spark.createDataFrame([(0, 0.0, 0, 3)], "v long, val double, word int, mask long")
    edges = spark.createDataFrame([(0, 1, 1.0, 0, 3)], "src long, dst long, w double, word int, mask long")
    plan = C.resolve(state, C.send(state, edges, SHORTEST), SHORTEST)._jdf.queryExecution().toString()
    assert "Cartesian" not in plan and "Python" not in plan and "Arrow" not in plan


def test_readers_and_writers(spark, tmp_path):
    from chronopath.sources import files

    edges = spark.createDataFrame([(0, 1, 2.5), (1, 2, 1.0)], "src long, dst long, w double")
    for kind in ("parquet", "orc", "json", "csv", "text"):
        files.write_edges(edges, f"{tmp_path}/{kind}", kind)
        assert sorted(files.read_edges(spark, f"{tmp_path}/{kind}", kind).collect()) == sorted(edges.collect())
    (tmp_path / "lines.txt").write_text("# a comment\n3\t4\n")
    assert [tuple(r) for r in files.read_edges(spark, f"{tmp_path}/lines.txt", "text").collect()] == [(3, 4, 1.0)]
    spark.dataSource.register(files.SyntheticUpdates)
    updates = spark.read.format("synthetic_updates").option("steps", 3).load()
    files.write_batches(updates, f"{tmp_path}/batches")
    some = files.read_batches(spark, f"{tmp_path}/batches", 2, 2)
    assert some.count() == 10 and "PartitionFilters: [isnotnull(step" in some._jdf.queryExecution().toString()


def test_table_function_and_local_solver(spark):
    from chronopath.functions import tables

    tables.register(spark)
    assert [r.snap for r in spark.sql("SELECT * FROM mask_to_snapshots(-9223372036854775807L, 1)").collect()] == [64, 127]
    rows = random_lives(3, vertices=10, snapshots=2)
    alive = spark.createDataFrame([(i, a, b, w) for a, b, w, born, died in rows for i in range(born, died)], "snap int, src long, dst long, w double")
    got = answer(tables.local_finish(alive, SHORTEST, 0))
    assert got == everywhere(rows, range(2), 0, SHORTEST)


def test_lifetimes_over_many_batches(spark, tmp_path):
    """One file a trigger, days out of order and bridging, a late row, and lives that only a timer ends."""
    from datetime import datetime, timedelta

    from chronopath.streaming import streams

    day = lambda n: datetime(2024, 1, 1, 12) + timedelta(days=n)
    batches = [
        [(1, "a", day(5)), (2, "a", day(0))],
        [(1, "a", day(1)), (1, "b", day(6))],
        [(1, "a", day(3)), (2, "a", day(20)), (1, "a", day(20))],
        [(1, "a", day(2)), (2, "a", day(17))],  # 2 is later than the delay allows, 17 is not
        [(9, "z", day(90))],
    ]
    for i, rows in enumerate(batches):
        spark.createDataFrame(rows, "user_id long, event_type string, ts timestamp").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("user_id long, event_type string, ts timestamp").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    found = {(r.user_id, r.event_type, r.born, r.died) for r in streams.run_to_table(streams.lifetimes(stream, "10 days")).collect()}
    at = lambda n: day(n).date()
    assert found == {(1, "a", at(1), at(6)), (2, "a", at(0), at(1)), (1, "b", at(6), at(7)), (1, "a", at(20), at(21)), (2, "a", at(17), at(21))}


def test_word_runs_link_items_inside_longer_lines(spark, tmp_path):
    """Items inside longer lines or wrapped otherwise are linked; null, empty and short texts are not."""
    from chronopath.sources import graphs

    docs = [(1, "we know that The quick\tbrown fox jumps over it"), (2, "the quick\nbrown fox jumps"), (3, "the quick brown fox"), (4, None), (5, ""), (6, "x the quick brown fox leaps")]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(7, "the quick brown fox jumps"), (8, "quick brown fox")], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    assert {(r.src, r.dst) for r in graphs.quiz(spark, str(tmp_path)).collect()} == {(-8, 1), (-8, 2)}
    assert {(r.src, r.dst, r.w) for r in graphs.lookalike(spark, str(tmp_path)).collect()} == {(1, 2, 2.0), (2, 1, 2.0)}


def test_runs_move_once_and_packed(spark, tmp_path, monkeypatch):
    """Stars of word runs over many packed pieces and repeated rows equal brute force; texts' runs go through one shuffle, pairs through another."""
    import random

    from chronopath.sources import graphs

    rng = random.Random(5)
    docs = [(rng.randrange(-3, 60), " ".join(rng.choice(["Um", "um", "dois", "três", "Água", "x" * 300]) for _ in range(rng.randrange(0, 30)))) for _ in range(90)] + [(None, "um dois um dois um dois"), (1 << 40, None)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    runs = {}
    for i, text in docs:
        words = (text or "").encode().lower().split()
        for k in range(len(words) - 4):
            if i is not None:
                runs.setdefault(tuple(words[k : k + 5]), set()).add(i)
    shared = {}
    for ids in runs.values():
        for i in ids - {min(ids)}:
            shared[min(ids), i] = shared.get((min(ids), i), 0) + 1
    monkeypatch.setattr(graphs, "RUNS_AT_ONCE", 50)
    found = graphs.lookalike(spark, str(tmp_path))
    assert found._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") == 2
    got = {(r.src, r.dst): r.w for r in found.collect()}
    assert got == {pair: 1.0 + n for (a, b), n in shared.items() for pair in ((a, b), (b, a))} and found.count() == 2 * len(shared)


def test_nearest_vectors_in_parts(spark, tmp_path, monkeypatch):
    """Several parts, ties, copies, a null vector and shorter ones: the same as the SQL, where a null distance comes last."""
    import random

    duckdb = pytest.importorskip("duckdb")
    from chronopath import oracles
    from chronopath.sources import graphs

    rng = random.Random(3)
    rows = [(i, [float(rng.randrange(4)) / 3 for _ in range(6)], i % 3) for i in range(90)] + [(100 + i, [0.5] * 6, 1) for i in range(30)]
    rows += [(200, None, 0), (201, [0.25, None, 0.5], 0), (202, [1.0] * 6, None), (203, [1.0] * 6, 7), (204, None, 7), (-5, [1e6, 0.0, 0.0, 0.0, 0.0, 1e-3], 2)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").coalesce(1).write.parquet(str(tmp_path / "embeddings.parquet"))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    monkeypatch.setattr(graphs, "PART_VECTORS", 7)
    monkeypatch.setattr(graphs, "VECTORS_AT_ONCE", 5)
    found = graphs.knn(spark, str(tmp_path))
    assert "BroadcastNestedLoop" not in (plan := found._jdf.queryExecution().executedPlan().toString()) and "zip_with" not in plan
    key = lambda r: (r[0], r[1], r[2] is None, r[2] or 0)
    assert sorted(map(tuple, found.collect()), key=key) == sorted(con.execute(oracles.GRAPH_SQL["knn"]).fetchall(), key=key)


def test_local_finish_gets_what_may_change_only(spark, tmp_path, monkeypatch):
    """The task of a snapshot gets far fewer rows than the graph has edges, with the answers of the other strategies; with too many rows the loops finish."""
    from chronopath import catalog
    from chronopath.functions import tables

    rows = [(i // 4, i % 4, pow(5, i * i + i // 3, 257) % 256, 0, float(1 + i % 9)) for i in range(3000)]
    spark.createDataFrame(rows, "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double").write.parquet(str(tmp_path / "lineitem.parquet"))
    given, finish = [], tables.local_finish
    lives_ = E.scripted(catalog.graphs.basket(spark, str(tmp_path)), 3, 10).cache()
    monkeypatch.setattr(catalog, "lifetimes", lambda *_: lives_)
    monkeypatch.setattr(tables, "local_finish", lambda rows, *rest: given.append(rows) or finish(rows, *rest))
    want = {(v, i): x for (v, i), x in answer(S.run("recompute_together", catalog.lifetimes(spark, str(tmp_path), 3), catalog.query("shortest", 3))[0]).items() if v}
    assert answer(catalog._local(spark, str(tmp_path))) == want and len(want) > 250, len(want)
    assert len(given) == 1 and given[0].count() * 4 < catalog.graphs.basket(spark, str(tmp_path)).count()
    monkeypatch.setattr(catalog, "LOCAL_ROWS", -1)
    assert answer(catalog._local(spark, str(tmp_path))) == want and len(given) == 1
