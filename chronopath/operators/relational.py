"""Operators that graph preparation and result reports need, as (DataFrame plan, SQL twin) pairs."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from chronopath.functions.masks import expand
from chronopath.oracles import BASKET
from chronopath.sources.graphs import basket, table

_REGISTRY: dict[str, tuple] = {}


def _op(sql: str | None, name: str | None = None):
    def add(f):
        _REGISTRY[name or f.__name__] = (f, sql)
        return f

    return add


def queries() -> dict:
    return {name: f for name, (f, _) in _REGISTRY.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _REGISTRY.items() if sql}


def _lives(spark, sf_dir) -> DataFrame:
    """Events as intervals of days: (id, a, b)."""
    day = F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date"))
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), F.col("user_id").alias("u"), day.alias("a"), (day + 1 + F.col("event_id") % 3).cast("int").alias("b"))


_LIVES = "lives AS (SELECT event_id AS id, user_id AS u, datediff('day', DATE '2024-01-01', ts::DATE)::INTEGER AS a, (datediff('day', DATE '2024-01-01', ts::DATE) + 1 + event_id % 3)::INTEGER AS b FROM events)"
G = f"WITH {BASKET} "


@_op("SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= 45")
def scan_basket_edges(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").where("l_quantity >= 45").select("l_orderkey", "l_partkey")


@_op("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def scan_event_props(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@_op(G + "SELECT src, dst, w FROM g WHERE w BETWEEN 5 AND 9 AND (src IN (1, 2, 3) OR dst % 7 = 0) AND nullif(w, 7) IS NOT NULL")
def op_predicates(spark, sf_dir):
    return basket(spark, sf_dir).where(F.col("w").between(5, 9) & (F.col("src").isin(1, 2, 3) | (F.col("dst") % 7 == 0)) & F.nullif("w", F.lit(7.0)).isNotNull())


@_op(f"WITH {_LIVES} SELECT id FROM lives WHERE a <= 10 AND 10 < b")
def op_snapshot_filter(spark, sf_dir):
    return _lives(spark, sf_dir).where("a <= 10 and 10 < b").select("id")


@_op(G + "SELECT a.src AS src, b.dst AS dst, min(a.w + b.w) AS w FROM g a JOIN g b ON a.dst = b.src WHERE a.src < 20 GROUP BY a.src, b.dst")
def op_two_hop(spark, sf_dir):
    g = basket(spark, sf_dir)
    a, b = g.where("src < 20").alias("a"), g.alias("b")
    return a.join(b, F.col("a.dst") == F.col("b.src")).groupBy("a.src", "b.dst").agg(F.min(F.col("a.w") + F.col("b.w")).alias("w"))


_HOP = "SELECT dst AS v, min(w) AS val FROM g WHERE src IN (0, 1, 2) GROUP BY dst"


@_op(G + _HOP)
def op_one_hop(spark, sf_dir):
    frontier = spark.createDataFrame([(i,) for i in range(3)], "src long")
    return basket(spark, sf_dir).hint("merge").join(frontier, "src").groupBy(F.col("dst").alias("v")).agg(F.min("w").alias("val"))


@_op(G + _HOP)
def op_one_hop_broadcast(spark, sf_dir):
    frontier = F.broadcast(spark.createDataFrame([(i,) for i in range(3)], "src long"))  # three rows
    return basket(spark, sf_dir).join(frontier, "src").groupBy(F.col("dst").alias("v")).agg(F.min("w").alias("val"))


@_op("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 100000)")
def op_semi_join(spark, sf_dir):
    dear = table(spark, sf_dir, "orders").where("o_totalprice > 100000").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, sf_dir, "customer").select("c_custkey").join(dear, "c_custkey", "left_semi")


@_op("SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 49)")
def op_anti_join(spark, sf_dir):
    much = table(spark, sf_dir, "lineitem").where("l_quantity > 49").select(F.col("l_partkey").alias("p_partkey"))
    return table(spark, sf_dir, "part").select("p_partkey").join(much, "p_partkey", "left_anti")


@_op("WITH a AS (SELECT src AS v, count(*) AS n_out FROM g GROUP BY src), b AS (SELECT dst AS v, count(*) AS n_in FROM g GROUP BY dst) SELECT coalesce(a.v, b.v) AS v, coalesce(n_out, 0) AS n_out, coalesce(n_in, 0) AS n_in FROM a FULL JOIN b ON a.v = b.v".replace("WITH a", G.rstrip() + ", a", 1))
def op_full_outer(spark, sf_dir):
    g = basket(spark, sf_dir)
    a, b = g.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("n_out")), g.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("n_in"))
    return a.join(b, "v", "full").select("v", F.coalesce("n_out", F.lit(0)).alias("n_out"), F.coalesce("n_in", F.lit(0)).alias("n_in"))


@_op(f"WITH {_LIVES} SELECT x.id AS x, y.id AS y FROM lives x JOIN lives y ON x.u = y.u AND x.id < y.id AND x.a < y.b AND y.a < x.b")
def op_life_overlap(spark, sf_dir):
    """Range join as an equi-join on days: each life is listed under the days it touches; a pair counts on its first common day."""
    days = _lives(spark, sf_dir).withColumn("day", F.explode(F.sequence("a", F.col("b") - 1)))
    x, y = days.alias("x"), days.alias("y")
    met = x.join(y, (F.col("x.u") == F.col("y.u")) & (F.col("x.day") == F.col("y.day")) & (F.col("x.id") < F.col("y.id")))
    return met.where(F.col("x.day") == F.greatest("x.a", "y.a")).select(F.col("x.id").alias("x"), F.col("y.id").alias("y"))


@_op("SELECT a.event_id AS x, b.event_id AS y FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = b.event_type AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def op_event_interval_join(spark, sf_dir):
    """Events of a user within an hour: hour buckets make it an equi-join, the later event in this bucket or the next."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3600000000).alias("h"))
    a, b = e.withColumn("h", F.explode(F.array("h", F.col("h") + 1))).alias("a"), e.alias("b")
    on = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.event_type") == F.col("b.event_type")) & (F.col("a.h") == F.col("b.h"))
    return a.join(b, on).where("b.ts > a.ts and b.ts <= a.ts + interval 1 hour").select(F.col("a.event_id").alias("x"), F.col("b.event_id").alias("y"))


@_op("SELECT q.event_id AS event_id, (SELECT arg_max(h.value, (h.ts, h.event_id)) FROM events h WHERE h.user_id = q.user_id AND h.event_type = 'purchase' AND h.ts < q.ts) AS value FROM events q WHERE q.event_type = 'click'")
def op_asof_weight(spark, sf_dir):
    """Latest purchase value of a user before each click: one pass over both, in time order, no join."""
    e = table(spark, sf_dir, "events").where("event_type in ('click', 'purchase')")
    late = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id", "value"))
    before = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(Window.unboundedPreceding, -1)
    return e.withColumn("last", F.max(late).over(before)).where("event_type = 'click'").select("event_id", F.col("last.value").alias("value"))


@_op("SELECT r_regionkey, snap FROM region, (SELECT range::INTEGER AS snap FROM range(4))")
def op_result_grid(spark, sf_dir):
    return table(spark, sf_dir, "region").select("r_regionkey", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("snap"))


for _name, _expr, _sql in (("hops", "1D", "1"), ("shortest", "2 + w", "2 + w"), ("widest", "least(20, w)", "least(20, w)"), ("narrowest", "greatest(5, w)", "greatest(5, w)"), ("likeliest", "1 / w", "1 / w")):
    _agg = "max" if _name in ("widest", "likeliest") else "min"
    _op(G + f"SELECT dst, {_agg}({_sql})::DOUBLE AS val FROM g GROUP BY dst", f"op_relax_once_{_name}")(lambda spark, sf_dir, e=_expr, a=_agg: basket(spark, sf_dir).groupBy("dst").agg(F.expr(f"{a}(cast({e} as double))").alias("val")))


@_op(G + "SELECT dst, min(w) AS val, arg_min(src, (w, src)) AS parent FROM g GROUP BY dst")
def op_best_parent(spark, sf_dir):
    return basket(spark, sf_dir).groupBy("dst").agg(F.min("w").alias("val"), F.min_by("src", F.struct("w", "src")).alias("parent"))


@_op("SELECT user_id, bit_or(1::BIGINT << (event_id % 60)::INTEGER) AS o, bit_and(1::BIGINT << (event_id % 60)::INTEGER) AS a, bit_xor(1::BIGINT << (event_id % 60)::INTEGER) AS x, bit_count(bit_or(1::BIGINT << (event_id % 60)::INTEGER))::INTEGER AS n FROM events GROUP BY user_id")
def op_bit_aggregates(spark, sf_dir):
    bit = F.expr("shiftleft(1L, cast(event_id % 60 as int))")
    return table(spark, sf_dir, "events").groupBy("user_id").agg(F.bit_or(bit).alias("o"), F.bit_and(bit).alias("a"), F.bit_xor(bit).alias("x"), F.bit_count(F.bit_or(bit)).alias("n"))


@_op(G + "SELECT count(DISTINCT dst) AS heads, count(DISTINCT (src, dst)) AS pairs FROM g")
def op_distinct_heads(spark, sf_dir):
    return basket(spark, sf_dir).agg(F.count_distinct("dst").alias("heads"), F.count_distinct("src", "dst").alias("pairs"))


@_op("SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS q FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def op_cube_measures(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))


@_op("SELECT event_type, count(*) FILTER (WHERE user_id % 2 = 0) AS even, count(*) FILTER (WHERE user_id % 2 = 1) AS odd FROM events GROUP BY event_type")
def op_pivot_results(spark, sf_dir):
    side = F.when(F.col("user_id") % 2 == 0, "even").otherwise("odd").alias("side")
    return table(spark, sf_dir, "events").select("event_type", side).groupBy("event_type").pivot("side", ["even", "odd"]).count().na.fill(0)


@_op(G + "SELECT src, list_sort(list(dst)) AS heads FROM g GROUP BY src")
def op_neighbors(spark, sf_dir):
    return basket(spark, sf_dir).groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("heads"))


@_op("SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type HAVING count(*) > 3")
def op_flapping_pairs(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).where("n > 3")


@_op("SELECT event_id, value - lag(value) OVER w AS change, avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS mean, first_value(value) OVER w AS first, nth_value(value, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_value_trend(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events").select("event_id", (F.col("value") - F.lag("value").over(w)).alias("change"), F.avg("value").over(w.rowsBetween(-2, 0)).alias("mean"), F.first("value").over(w).alias("first"), F.nth_value("value", 2).over(w).alias("second"))


@_op("SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS d, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey)::INTEGER AS q, percent_rank() OVER w AS p, cume_dist() OVER w AS c FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def op_ranks(spark, sf_dir):
    w = Window.partitionBy("p_brand").orderBy("p_size")
    return table(spark, sf_dir, "part").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).alias("q"), F.percent_rank().over(w).alias("p"), F.cume_dist().over(w).alias("c"))


@_op("SELECT event_id, bit_or(1::BIGINT << (event_id % 60)::INTEGER) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS served FROM events")
def op_mask_resolve(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, sf_dir, "events").select("event_id", F.bit_or(F.expr("shiftleft(1L, cast(event_id % 60 as int))")).over(w).alias("served"))


@_op(f"WITH {_LIVES}, d AS (SELECT DISTINCT u, a FROM lives), i AS (SELECT *, a - row_number() OVER (PARTITION BY u ORDER BY a) AS k FROM d) SELECT u, min(a) AS first, max(a) AS last FROM i GROUP BY u, k")
def op_mask_runs(spark, sf_dir):
    days = _lives(spark, sf_dir).select("u", "a").distinct().withColumn("k", F.col("a") - F.row_number().over(Window.partitionBy("u").orderBy("a")))
    return days.groupBy("u", "k").agg(F.min("a").alias("first"), F.max("a").alias("last")).drop("k")


@_op(G + "SELECT dst, count(*) AS n FROM g GROUP BY dst ORDER BY n DESC, dst LIMIT 10 OFFSET 2")
def op_topk_changed(spark, sf_dir):
    return basket(spark, sf_dir).groupBy("dst").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "dst").offset(2).limit(10)


@_op("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
def op_topk_per_group(spark, sf_dir):
    r = F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return table(spark, sf_dir, "orders").withColumn("r", r).where("r <= 2").select("o_custkey", "o_orderkey")


def _sides(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("user_id", "event_type", "event_id")
    return [e.where(f"event_id % 3 = {k}").select("user_id", "event_type") for k in range(3)]


_SIDES = [f"SELECT user_id, event_type FROM events WHERE event_id % 3 = {k}" for k in range(3)]


@_op(" INTERSECT ".join(_SIDES))
def op_core_by_intersect(spark, sf_dir):
    return reduce(DataFrame.intersect, _sides(spark, sf_dir))


@_op(" UNION ".join(_SIDES))
def op_hull_by_union(spark, sf_dir):
    return reduce(DataFrame.unionByName, _sides(spark, sf_dir)).distinct()


@_op(" EXCEPT ALL ".join(_SIDES[:2]))
def op_additions_by_except(spark, sf_dir):
    a, b, _ = _sides(spark, sf_dir)
    return a.exceptAll(b)


@_op(" INTERSECT ALL ".join(_SIDES[:2]))
def op_intersect_all(spark, sf_dir):
    a, b, _ = _sides(spark, sf_dir)
    return a.intersectAll(b)


@_op("SELECT event_id, abs(value - 50) AS a, ceil(value)::BIGINT AS c, floor(value)::BIGINT AS f, round(ln(value + 1), 6) AS l, round(sqrt(value), 6) AS s, event_id & 12 AS b, event_id | 3 AS o, xor(event_id, 5) AS x, least(value, 10) AS m FROM events")
def op_math_bits(spark, sf_dir):
    v, i = F.col("value"), F.col("event_id")
    return table(spark, sf_dir, "events").select("event_id", F.abs(v - 50).alias("a"), F.ceil(v).alias("c"), F.floor(v).alias("f"), F.round(F.log(v + 1), 6).alias("l"), F.round(F.sqrt(v), 6).alias("s"), i.bitwiseAND(12).alias("b"), i.bitwiseOR(3).alias("o"), i.bitwiseXOR(5).alias("x"), F.least(v, F.lit(10.0)).alias("m"))


@_op("SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, len(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1))::INTEGER AS links, lower(substr(url, 1, 12)) AS head, md5(url) AS h FROM pages")
def op_strings(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.size(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), 1)).alias("links"), F.lower(F.substring("url", 1, 12)).alias("head"), F.md5(F.col("url").cast("binary")).alias("h"))


@_op("SELECT date_trunc('day', ts)::DATE AS day, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def op_tumbling_days(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.date_trunc("day", "ts").cast("date").alias("day")).agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("users"))


@_op("SELECT (DATE '2024-01-01' + k::INTEGER) AS first, count(*) AS n FROM events, range(24) AS t(k) WHERE ts >= DATE '2024-01-01' + k::INTEGER AND ts < DATE '2024-01-08' + k::INTEGER GROUP BY 1")
def op_sliding_lifetimes(spark, sf_dir):
    """Windows of seven days, a day apart, that lie inside the first thirty days."""
    w = F.window("ts", "7 days", "1 day", "0 days")
    return table(spark, sf_dir, "events").groupBy(w.alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").cast("date").alias("first"), "n").where("first >= date'2024-01-01' and first < date'2024-01-25'")


@_op(f"WITH {_LIVES} SELECT id, unnest(range(a, b))::INTEGER AS snap FROM lives")
def op_expand_masks(spark, sf_dir):
    bits = F.expr("shiftleft(-1L, a) & shiftrightunsigned(-1L, 64 - b)")
    return expand(_lives(spark, sf_dir).select("id", bits.alias("mask"), F.lit(0).alias("word"))).select("id", "snap")


@_op("SELECT event_type, count(*) AS n, sum(user_id)::BIGINT AS s FROM events GROUP BY event_type")
def op_measure_map(spark, sf_dir):
    """Through a map and JSON and back."""
    own = table(spark, sf_dir, "events").groupBy("event_type").agg(F.map_from_entries(F.array(F.struct(F.lit("n"), F.count("*")), F.struct(F.lit("s"), F.sum("user_id")))).alias("m"))
    back = own.select("event_type", F.from_json(F.to_json("m"), "map<string,bigint>").alias("m"))
    return back.select("event_type", F.col("m")["n"].alias("n"), F.col("m")["s"].alias("s"))


@_op("WITH RECURSIVE r(v, hop) AS (SELECT 0::BIGINT, 0 UNION SELECT g.dst, hop + 1 FROM r JOIN gg g ON g.src = r.v WHERE hop < 2) SELECT v, min(hop)::INTEGER AS hop FROM r GROUP BY v".replace("WITH RECURSIVE r", f"WITH RECURSIVE {BASKET}, gg AS (SELECT * FROM g WHERE w = 1), r", 1))
def op_reach_recursive(spark, sf_dir):
    """Vertices within two edges of weight one, by two joins."""
    g = basket(spark, sf_dir).where("w = 1")
    now = spark.createDataFrame([(0, 0)], "v long, hop int")
    for hop in (1, 2):
        now = now.unionByName(now.join(g, F.col("v") == F.col("src")).select(F.col("dst").alias("v"), F.lit(hop).alias("hop")))
    return now.groupBy("v").agg(F.min("hop").alias("hop"))


@_op("SELECT p_partkey FROM part WHERE (p_partkey * 48271 % 2147483647) % 10 = 0")
def op_sources_sample(spark, sf_dir):
    """A tenth of the parts, by a portable hash of the key."""
    return table(spark, sf_dir, "part").where("(p_partkey * 48271 % 2147483647) % 10 = 0").select("p_partkey")


@_op("SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM orders i WHERE i.o_orderpriority = o.o_orderpriority)")
def op_correlated(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    mean = o.groupBy("o_orderpriority").agg((1.5 * F.avg("o_totalprice")).alias("m"))
    return o.join(mean, "o_orderpriority").where("o_totalprice > m").select("o_orderkey")


@_op("SELECT dst AS v, min(w)::DOUBLE AS val FROM g GROUP BY dst".replace("SELECT", G + "SELECT", 1))
def sql_surface(spark, sf_dir):
    """The same through a view and SQL."""
    basket(spark, sf_dir).createOrReplaceTempView("chronopath_edges")
    return spark.sql("SELECT dst AS v, min(w) AS val FROM chronopath_edges GROUP BY dst")


@_op(G + "SELECT percentile_cont(0.5) WITHIN GROUP (ORDER BY w) AS median, max(w) - min(w) AS width FROM g")
def op_weight_quantiles(spark, sf_dir):
    return basket(spark, sf_dir).agg(F.percentile("w", 0.5).alias("median"), (F.max("w") - F.min("w")).alias("width"))


@_op("SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n, max(o_totalprice) AS top FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def op_grouping_sets(spark, sf_dir):
    """Totals by status, by priority and of all."""
    o = table(spark, sf_dir, "orders").select(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"), "o_totalprice")
    return o.groupingSets([["status"], ["priority"], []], "status", "priority").agg(F.count("*").alias("n"), F.max("o_totalprice").alias("top"))


@_op("SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def op_rollup(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"))
    return o.rollup("status", "priority").agg(F.count("*").alias("n"))


@_op("WITH m AS (SELECT o_orderpriority AS priority, min(o_totalprice) AS low, max(o_totalprice) AS top FROM orders GROUP BY 1) SELECT priority, 'low' AS measure, low AS value FROM m UNION ALL SELECT priority, 'top', top FROM m")
def op_unpivot(spark, sf_dir):
    """A column for each measure, then a row for each."""
    m = table(spark, sf_dir, "orders").groupBy(F.col("o_orderpriority").alias("priority")).agg(F.min("o_totalprice").alias("low"), F.max("o_totalprice").alias("top"))
    return m.unpivot("priority", ["low", "top"], "measure", "value")


@_op(None)
def op_approx_heads(spark, sf_dir):
    return basket(spark, sf_dir).agg(F.approx_count_distinct("dst").alias("heads"), F.percentile_approx("w", 0.5).alias("median"))
