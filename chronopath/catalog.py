"""Registered queries of the engine and their SQL twins."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath import measures, oracles
from chronopath.functions import tables
from chronopath.functions.algebra import ALGEBRAS, LIKELIEST_LOG, PathAlgebra
from chronopath.functions.masks import expand
from chronopath.operators import relational
from chronopath.plans import concurrent as C
from chronopath.plans import evolve as E
from chronopath.plans import residual as R
from chronopath.plans import sharing
from chronopath.plans import strategies as S
from chronopath.plans.fixpoint import solve_full
from chronopath.sources import graphs
from chronopath.storage import Stored, store
from chronopath.streaming import streams

SOURCE, BATCH = 0, 100
LONG, SHORT = 64, 3  # snapshots of the concurrent strategies; of those that loop over snapshots
#: The published sweeps: snapshots, and batches as 1/3, 2/3, 1, 4/3 and 5/3 of the standard one.
SWEEP_SNAPSHOTS, SWEEP_BATCHES = (32, 64, 128), (33, 67, 100, 133, 167)
#: Edges and starts (rows over all snapshots) up to which a task finishes a snapshot by itself.
LOCAL_ROWS = 2_000_000
WIDTHS = [1.0, 2.0, 4.0, 8.0, 16.0]  # edges of the buckets of bound widths
TOGETHER = ("recompute_together", "residual_conc", "residual_conc_shared", "core_conc")

_memo: dict[tuple, object] = {}


def _once(spark, key: tuple, make):
    """A stored table is made once a session and reused by the queries that need it."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _memo:
        _memo[key] = make()
    return _memo[key]


def lifetimes(spark, sf_dir, snapshots, batch=BATCH) -> DataFrame:
    return _once(spark, ("lt", sf_dir, snapshots, batch), lambda: store(E.scripted(graphs.basket(spark, sf_dir), snapshots, batch), "lifetimes"))


def query(name: str, snapshots: int) -> S.PathQuery:
    return S.PathQuery(SOURCE, ALGEBRAS[name], tuple(range(snapshots)))


def prepared(spark, sf_dir, name, snapshots=LONG, batch=BATCH) -> S.Prepared:
    make = lambda: S.prepare(lifetimes(spark, sf_dir, snapshots, batch), query(name, snapshots), S.RunStats("prepare", name))
    return _once(spark, ("prepared", sf_dir, name, snapshots, batch), make)


def results(spark, sf_dir, name, strategy, snapshots) -> DataFrame:
    def make():
        out, _ = S.run(strategy, lifetimes(spark, sf_dir, snapshots), query(name, snapshots))
        return store(out.where(F.col("v") != SOURCE), "results")

    return _once(spark, ("results", sf_dir, name, strategy, snapshots), make)


def _full(name, spark, sf_dir):
    return solve_full(ALGEBRAS[name].checked(graphs.basket(spark, sf_dir)), SOURCE, ALGEBRAS[name]).where(F.col("v") != SOURCE).select("v", "val")


def _logarithms(spark, sf_dir):
    found = solve_full(LIKELIEST_LOG.checked(graphs.basket(spark, sf_dir)), SOURCE, LIKELIEST_LOG).where(F.col("v") != SOURCE)
    return found.select("v", F.round("val", 6).alias("val"))


def _widths(name, spark, sf_dir):
    return measures.bound_widths(prepared(spark, sf_dir, name).bound, WIDTHS)


def _degree(name, spark, sf_dir):
    return measures.average_degree(graphs.GRAPHS[name](spark, sf_dir))


def _core(spark, sf_dir):
    return prepared(spark, sf_dir, "shortest").core


def _hull(spark, sf_dir):
    return E.hull_graph(E.classified(lifetimes(spark, sf_dir, LONG), range(LONG), ALGEBRAS["shortest"]))


def _batches(spark, sf_dir):
    return E.batches(lifetimes(spark, sf_dir, LONG), LONG)


def _round_trip(spark, sf_dir):
    lt = lifetimes(spark, sf_dir, LONG)
    return E.lifetimes_from_batches(E.snapshot(lt, 0), E.batches(lt, LONG), LONG)


def _bounds(name, spark, sf_dir):
    return prepared(spark, sf_dir, name).bound.where(F.col("v") != SOURCE)


def _stable(name, spark, sf_dir):
    return prepared(spark, sf_dir, name).bound.where(F.col("core_val").eqNullSafe(F.col("hull_val")) & (F.col("v") != SOURCE)).select("v", F.col("core_val").alias("val"))


def _versioned(name, spark, sf_dir):
    p = prepared(spark, sf_dir, name)
    return C.versioned_graph(p.residual, p.trimmed, range(LONG)).select("src", "dst", "w", "mask")


def _loop(name, spark, sf_dir):
    p = prepared(spark, sf_dir, name)
    return R.loop_edges(C.versioned_graph(p.residual, p.trimmed, range(LONG)), p.unstable).select("src", "dst", "w", "mask")


def _share(name, spark, sf_dir):
    return measures.unchanged_share(results(spark, sf_dir, name, "residual_conc", LONG), LONG)


def _sizes(name, spark, sf_dir, snapshots=LONG, batch=BATCH):
    p = prepared(spark, sf_dir, name, snapshots, batch)
    return measures.sizes(p.core, p.additions, p.bound, p.unstable, p.residual, p.trimmed)


def _detection(name, spark, sf_dir):
    bound = prepared(spark, sf_dir, name).bound.where(F.col("v") != SOURCE)
    return measures.detection(bound, results(spark, sf_dir, name, "residual_conc", LONG), LONG)


def _sweep(values, by, spark, sf_dir):
    frames = [_sizes("shortest", spark, sf_dir, **{by: x}).withColumn(by, F.lit(x)) for x in values]
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out.select(by, "core_edges", "residual_edges", "vertices", "unstable", "added_total", "trimmed_total")


def _tree(spark, sf_dir):
    lt = lifetimes(spark, sf_dir, 8)
    counts = {(r["born"], r["died"]): r["n"] for r in E.bursts_table(lt).collect()}
    return spark.createDataFrame(sharing.tree_sizes(counts, sharing.plan_tree(0, 7)), "lo int, hi int, n_added long")


def _scaled(spark, sf_dir):
    """An algebra of the user's own: each further edge counts its weight plus a tenth of the way so far."""
    algebra = PathAlgebra("scaled", lambda val, w: val * 1.1 + w, "{val} * 1.1 + {w}", "min", 0.0)
    return solve_full(graphs.basket(spark, sf_dir), SOURCE, algebra).where(F.col("v") != SOURCE).select("v", F.round("val", 6).alias("val"))


def _local(spark, sf_dir):
    """Bounds settle the stable vertices by the loops; what may change is finished in one task a snapshot, or by the loops where it is too much for one."""
    p, asked, chosen = prepared(spark, sf_dir, "shortest", SHORT), query("shortest", SHORT), range(SHORT)
    loop = Stored(R.loop_edges(C.versioned_graph(p.residual, p.trimmed, chosen), p.unstable), "versioned")
    begun = C.everywhere(p.core_state.join(p.unstable, "v", "left_semi"), chosen)
    entering = C.send(C.everywhere(p.core_state.join(p.unstable, "v", "left_anti"), chosen), p.trimmed, asked.algebra).drop("met")
    starts = Stored(begun.unionByName(entering), "starts")
    if loop.seen["rows"] + starts.seen["rows"] > LOCAL_ROWS:
        return results(spark, sf_dir, "shortest", "residual_conc", SHORT)
    found = tables.local_finish(expand(loop.df), asked.algebra, SOURCE, expand(starts.df))
    return found.unionByName(S.stable_rows(p, asked).select("v", "snap", "val")).where(F.col("v") != SOURCE)


def _by_table_function(spark, sf_dir):
    tables.register(spark)
    E.masked(lifetimes(spark, sf_dir, SHORT), range(SHORT)).createOrReplaceTempView("chronopath_masked")
    return spark.sql("SELECT src, dst, snap FROM chronopath_masked, LATERAL mask_to_snapshots(mask, word)")


def _streamed(spark, sf_dir):
    lt = lifetimes(spark, sf_dir, SHORT)
    return streams.run_incremental(E.snapshot(lt, 0), store(E.batches(lt, SHORT)), SOURCE, ALGEBRAS["shortest"]).where(F.col("v") != SOURCE)


def queries() -> dict:
    out = {"udf_custom_algebra": _scaled, "udf_local_finish": _local, "udtf_expand_mask": _by_table_function, "stream_incremental_shortest": _streamed}
    out |= {"entry_shortest": lambda spark, sf_dir: S.run("residual_conc", lifetimes(spark, sf_dir, 8, 20), query("shortest", 8))[0]}
    out |= {f"full_{a}": partial(_full, a) for a in ALGEBRAS}
    out |= {"core_edges": _core, "hull_edges": _hull, "batches_basket": _batches, "lifetimes_round_trip": _round_trip}
    out["addition_sets"] = lambda spark, sf_dir: prepared(spark, sf_dir, "shortest").additions.select("src", "dst", "w", "mask")
    out["lifetimes_basket"] = lambda spark, sf_dir: lifetimes(spark, sf_dir, LONG)
    out["masks_basket"] = lambda spark, sf_dir: E.masked(lifetimes(spark, sf_dir, LONG), range(LONG)).select("src", "dst", "w", "mask")
    for a in ALGEBRAS:
        out |= {f"bounds_{a}": partial(_bounds, a), f"stable_vertices_{a}": partial(_stable, a)}
        out[f"residual_edges_{a}"] = lambda spark, sf_dir, a=a: prepared(spark, sf_dir, a).residual
        out[f"trimmed_additions_{a}"] = lambda spark, sf_dir, a=a: prepared(spark, sf_dir, a).trimmed.select("src", "dst", "w", "mask")
        out |= {f"versioned_{a}": partial(_versioned, a), f"loop_edges_{a}": partial(_loop, a)}
        for s in S.STRATEGIES:
            out[f"results_{s}_{a}"] = lambda spark, sf_dir, a=a, s=s: results(spark, sf_dir, a, s, LONG if s in TOGETHER else SHORT)
        out |= {f"w1_unchanged_share_{a}": partial(_share, a), f"w3_residual_sizes_{a}": partial(_sizes, a), f"w4_detection_{a}": partial(_detection, a)}
    out["w6_sizes_by_s"] = partial(_sweep, SWEEP_SNAPSHOTS, "snapshots")
    out["w7_sizes_by_batch"] = partial(_sweep, SWEEP_BATCHES, "batch")
    out["sharing_tree_additions"] = _tree
    out["full_likeliest_log"] = _logarithms
    out |= {f"bound_width_{a}": partial(_widths, a) for a in ("hops", "shortest", "narrowest")}
    out |= {f"average_degree_{g}": partial(_degree, g) for g in ("basket", "trade", "supply")}
    out |= {f"graph_{g}_edges": f for g, f in graphs.GRAPHS.items()}
    return out | relational.queries() | streams.queries()


def _sizes_sql(a, snapshots=LONG, batch=BATCH) -> str:
    counts = """(SELECT count(*) FROM core) AS core_edges, (SELECT count(*) FROM residual) AS residual_edges, (SELECT count(*) FROM bounds) AS vertices,
      (SELECT count(*) FROM unstable) AS unstable, (SELECT count(DISTINCT (src, dst)) FROM adds) AS added_distinct, (SELECT count(*) FROM adds) AS added_total,
      (SELECT count(DISTINCT (src, dst)) FROM trimmed) AS trimmed_distinct, (SELECT count(*) FROM trimmed) AS trimmed_total"""
    shares = "residual_edges / nullif(core_edges, 0) AS edge_share, unstable / nullif(vertices, 0) AS vertex_share, added_total - added_distinct AS redundant, CASE WHEN added_total > 0 THEN trimmed_total / added_total END AS kept_share"
    return oracles.recursive(oracles.scripted(snapshots, batch), oracles.bounds(ALGEBRAS[a], SOURCE)) + f" SELECT *, {shares} FROM (SELECT {counts})"


def oracle_sql() -> dict[str, str]:
    script, with_ = oracles.scripted(LONG, BATCH), oracles.recursive
    bits = f"SELECT src, dst, w, {oracles.mask()} AS mask FROM lt"
    partly = f"SELECT src, dst, w, {oracles.mask()} AS mask FROM lt WHERE NOT (born = 0 AND died = {LONG})"
    short = with_(oracles.scripted(SHORT, BATCH), oracles.per_snapshot(ALGEBRAS["shortest"], SOURCE))
    scaled = PathAlgebra("scaled", None, "{val} * 1.1 + {w}", "min", 0.0)
    out = {
        "udf_custom_algebra": with_(oracles.BASKET, oracles.paths("res", "SELECT 0 AS snap, src, dst, w FROM g", scaled, SOURCE)) + f" SELECT v, round(val, 6) AS val FROM res WHERE v <> {SOURCE}",
        "udf_local_finish": short + f" SELECT v, snap, val FROM res WHERE v <> {SOURCE}",
        "stream_incremental_shortest": short + f" SELECT v, val FROM res WHERE v <> {SOURCE} AND snap = {SHORT - 1}",
        "udtf_expand_mask": with_(oracles.scripted(SHORT, BATCH)) + " SELECT src, dst, snap FROM lt, snaps WHERE born <= snap AND snap < died",
        "entry_shortest": with_(oracles.scripted(8, 20), oracles.per_snapshot(ALGEBRAS["shortest"], SOURCE)) + " SELECT v, snap, val FROM res",
        "core_edges": with_(script, oracles.CORE) + " SELECT * FROM core",
        "hull_edges": with_(script, oracles.HULL) + " SELECT * FROM hull",
        "batches_basket": with_(script) + f" SELECT born AS step, 'add' AS op, src, dst, w FROM lt WHERE born > 0 UNION ALL SELECT died, 'del', src, dst, w FROM lt WHERE died < {LONG}",
        "lifetimes_basket": with_(script) + " SELECT * FROM lt",
        "lifetimes_round_trip": with_(script) + " SELECT * FROM lt",
        "addition_sets": with_(script) + " " + partly,
        "masks_basket": with_(script) + " " + bits,
    }
    for a, algebra in ALGEBRAS.items():
        bounds = with_(script, oracles.bounds(algebra, SOURCE))
        out[f"full_{a}"] = with_(oracles.BASKET, oracles.paths("res", "SELECT 0 AS snap, src, dst, w FROM g", algebra, SOURCE)) + f" SELECT v, val FROM res WHERE v <> {SOURCE}"
        out[f"bounds_{a}"] = bounds + f" SELECT * FROM bounds WHERE v <> {SOURCE}"
        out[f"stable_vertices_{a}"] = bounds + f" SELECT v, core_val AS val FROM bounds WHERE core_val IS NOT DISTINCT FROM hull_val AND v <> {SOURCE}"
        out[f"residual_edges_{a}"] = bounds + " SELECT * FROM residual"
        trimmed = f"{partly} AND dst IN (SELECT v FROM unstable)"
        out[f"trimmed_additions_{a}"] = f"{bounds} {trimmed}"
        whole = f"SELECT src, dst, w, -1::BIGINT AS mask FROM residual UNION ALL {trimmed}"
        out[f"versioned_{a}"] = f"{bounds} {whole}"
        out[f"loop_edges_{a}"] = f"{bounds} SELECT * FROM ({whole}) WHERE src IN (SELECT v FROM unstable)"
        for s in S.STRATEGIES:
            n = LONG if s in TOGETHER else SHORT
            out[f"results_{s}_{a}"] = with_(oracles.scripted(n, BATCH), oracles.per_snapshot(algebra, SOURCE)) + f" SELECT v, snap, val FROM res WHERE v <> {SOURCE}"
        res = with_(script, oracles.bounds(algebra, SOURCE), oracles.per_snapshot(algebra, SOURCE), f"own AS (SELECT v, count(*) = {LONG} AND min(val) = max(val) AS same FROM res WHERE v <> {SOURCE} GROUP BY v)")
        out[f"w1_unchanged_share_{a}"] = res + " SELECT count(*) AS vertices, sum(same::BIGINT)::BIGINT AS unchanged, avg(same::INTEGER) AS share FROM own"
        out[f"w4_detection_{a}"] = res + f""", st AS (SELECT v FROM bounds WHERE core_val = hull_val AND v <> {SOURCE}), n AS (
          SELECT (SELECT count(*) FROM st) AS stable, (SELECT count(*) FROM own WHERE same) AS unchanged, (SELECT count(*) FROM st JOIN own USING (v) WHERE same) AS found)
          SELECT *, stable - found AS unsafe, found / nullif(unchanged, 0) AS recall FROM n"""
        out[f"w3_residual_sizes_{a}"] = _sizes_sql(a)
    for a in ("hops", "shortest", "narrowest"):
        bucket = " + ".join(f"(upper - lower >= {e})::INTEGER" for e in WIDTHS)
        out[f"bound_width_{a}"] = with_(script, oracles.bounds(ALGEBRAS[a], SOURCE)) + f" SELECT ({bucket})::INTEGER AS bucket, count(*) AS n FROM bounds WHERE core_val <> hull_val GROUP BY 1"
    for g in ("basket", "trade", "supply"):
        out[f"average_degree_{g}"] = f"WITH e AS ({oracles.GRAPH_SQL[g]}), n AS (SELECT (SELECT count(*) FROM e) AS edges, (SELECT count(*) FROM (SELECT src FROM e UNION SELECT dst FROM e)) AS vertices) SELECT *, edges / vertices AS degree, 2 * edges / vertices AS degree_both FROM n"
    out["full_likeliest_log"] = with_(oracles.BASKET, oracles.paths("res", "SELECT 0 AS snap, src, dst, w FROM g", LIKELIEST_LOG, SOURCE)) + f" SELECT v, round(val, 6) AS val FROM res WHERE v <> {SOURCE}"
    columns = "core_edges, residual_edges, vertices, unstable, added_total, trimmed_total"
    out["w6_sizes_by_s"] = " UNION ALL ".join(f"SELECT {n}::INTEGER AS snapshots, {columns} FROM ({_sizes_sql('shortest', n)})" for n in SWEEP_SNAPSHOTS)
    out["w7_sizes_by_batch"] = " UNION ALL ".join(f"SELECT {n}::INTEGER AS batch, {columns} FROM ({_sizes_sql('shortest', LONG, n)})" for n in SWEEP_BATCHES)
    ranges = [(lo, hi, p[0], p[1]) for lo, hi, *p in sharing.plan_tree(0, 7)]
    through = lambda i, j: f"count(*) FILTER (WHERE born <= {i} AND died > {j})"
    rows = [f"SELECT {i}::INTEGER AS lo, {j}::INTEGER AS hi, {through(i, j)}{'' if p is None else ' - ' + through(p, q)} AS n_added FROM lt" for i, j, p, q in ranges]
    out["sharing_tree_additions"] = with_(oracles.scripted(8, BATCH)) + " " + " UNION ALL ".join(rows)
    out |= {f"graph_{g}_edges": sql for g, sql in oracles.GRAPH_SQL.items()}
    return out | relational.oracle_sql() | streams.oracle_sql()
