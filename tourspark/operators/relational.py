"""Relational operators that users of the methods need, each on the given tables."""

from __future__ import annotations


from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tourspark import graphs
from tourspark.functions import graph as fg
from tourspark.functions.graph import Graph
from tourspark.operators import graph_sql as sql
from tourspark.operators import methods
from tourspark.operators.registry import query
from tourspark.plans import measures, metagraph
from tourspark.session import read_table, stage, stage_path

_MONEY = "decimal(18,2)"


def _stats(spark, sf_dir, name="event_trail") -> DataFrame:
    _, tree, rows = methods.levelled(spark, sf_dir, name)
    return measures.level_stats(rows, tree)


_ST = sql.stats("event_trail")
_KINDS = "kd AS (SELECT level, part, 'I' AS kind, i AS n FROM st UNION ALL SELECT level, part, 'OB', ob FROM st UNION ALL SELECT level, part, 'EB', eb FROM st)"


def _kinds(spark, sf_dir) -> DataFrame:
    return _stats(spark, sf_dir).select("level", "part", F.explode(F.create_map(F.lit("I"), "i", F.lit("OB"), "ob", F.lit("EB"), "eb")).alias("kind", "n"))


# Scans, projections, joins ---------------------------------------------------------------
@query("op_scan_project_filter", "SELECT l_orderkey, l_linenumber, CAST(CAST(l_extendedprice AS DECIMAL(18,2)) * 100 AS BIGINT) AS cents FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01' AND l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R')")
def op_scan_project_filter(spark, sf_dir):
    rows = read_table(spark, sf_dir, "lineitem")
    day = lambda d: F.lit(d).cast("timestamp_ntz")
    kept = rows.where((F.col("l_shipdate") >= day("1995-01-01")) & (F.col("l_shipdate") < day("1996-01-01")) & F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R"))
    return kept.select("l_orderkey", "l_linenumber", (F.col("l_extendedprice").cast(_MONEY) * 100).cast("long").alias("cents"))


@query("op_nation_region_broadcast", "SELECT r_name, n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def op_nation_region_broadcast(spark, sf_dir):
    read = lambda t: read_table(spark, sf_dir, t)
    # 25 nations and 5 regions at any scale
    small = read("nation").join(F.broadcast(read("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return read("customer").join(F.broadcast(small), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name", "n_name").agg(F.count("*").alias("customers"))


@query("op_order_line_sortmerge", "SELECT o_orderpriority, count(*) AS lines, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS price FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL")
def op_order_line_sortmerge(spark, sf_dir):
    orders = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    lines = read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_extendedprice").hint("merge")
    return orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("lines"), F.sum(F.col("l_extendedprice").cast(_MONEY)).cast("double").alias("price"))


@query("op_shuffle_hash_hint", "SELECT p_brand, count(*) AS lines FROM part JOIN lineitem ON p_partkey = l_partkey GROUP BY ALL")
def op_shuffle_hash_hint(spark, sf_dir):
    part = read_table(spark, sf_dir, "part").select("p_partkey", "p_brand").hint("shuffle_hash")
    return read_table(spark, sf_dir, "lineitem").select("l_partkey").join(part, F.col("p_partkey") == F.col("l_partkey")).groupBy("p_brand").agg(F.count("*").alias("lines"))


@query("op_semi_odd_vertices", sql.with_(sql.edges("supply_multi"), "SELECT u, v, count(*) AS n FROM e WHERE u IN (SELECT v FROM (SELECT v, count(*) AS d FROM (SELECT unnest([u, v]) AS v FROM e) GROUP BY v) WHERE d % 2 = 1) GROUP BY ALL"))
def op_semi_odd_vertices(spark, sf_dir):
    g = Graph.from_edges(graphs.supply_multi(spark, sf_dir))
    odd = fg.odd_vertices(g).select(F.col("v").alias("u"))
    return g.edges.join(odd, "u", "left_semi").groupBy("u", "v").agg(F.count("*").alias("n"))


@query("op_anti_unsold_parts", "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 49)")
def op_anti_unsold_parts(spark, sf_dir):
    sold = read_table(spark, sf_dir, "lineitem").where("l_quantity > 49").select("l_partkey")
    return read_table(spark, sf_dir, "part").select("p_partkey").join(sold, F.col("p_partkey") == F.col("l_partkey"), "left_anti")


@query("op_outer_degree_change", sql.with_(sql.edges("order_part_repaired"), "SELECT v, coalesce(a.n, 0) AS before, coalesce(b.n, 0) AS after FROM (SELECT v, count(*) AS n FROM (SELECT unnest([u, v]) AS v FROM e0) GROUP BY v) a FULL JOIN (SELECT v, count(*) AS n FROM (SELECT unnest([u, v]) AS v FROM e) GROUP BY v) b USING (v) WHERE a.n IS DISTINCT FROM b.n"))
def op_outer_degree_change(spark, sf_dir):
    g = Graph.from_edges(graphs.order_part(spark, sf_dir))
    a, b = fg.degrees(g).withColumnRenamed("deg", "x"), fg.degrees(fg.repair_parity(g)).withColumnRenamed("deg", "y")
    zero = lambda c: F.coalesce(c, F.lit(0))
    return a.join(b, "v", "full").where(~F.col("x").eqNullSafe(F.col("y"))).select("v", zero("x").alias("before"), zero("y").alias("after"))


@query("op_theta_balance", "SELECT s_suppkey, count(*) AS richer FROM supplier JOIN customer ON c_nationkey = s_nationkey AND c_acctbal > s_acctbal GROUP BY s_suppkey")
def op_theta_balance(spark, sf_dir):
    s, c = read_table(spark, sf_dir, "supplier"), read_table(spark, sf_dir, "customer")
    return s.join(c, (F.col("c_nationkey") == F.col("s_nationkey")) & (F.col("c_acctbal") > F.col("s_acctbal"))).groupBy("s_suppkey").agg(F.count("*").alias("richer"))


@query("op_cross_parts", sql.with_(sql.tree("supplier_loops"), "SELECT x.leaf AS a, y.leaf AS b, coalesce(w, 0) AS weight FROM p0 x JOIN p0 y ON x.leaf < y.leaf LEFT JOIN m0 ON a = x.leaf AND b = y.leaf"))
def op_cross_parts(spark, sf_dir):
    """All pairs of parts, those without an edge with weight 0: n(n-1)/2 rows by definition."""
    slots = spark.range(8).select(F.col("id").cast("int").alias("a"), F.explode(F.sequence(F.lit(0), F.lit(7))).alias("b")).where("a < b")
    meta = metagraph.meta_graph(methods.held(spark, sf_dir, "supplier_loops")).select("a", "b", "weight")
    return slots.join(meta, ["a", "b"], "left").select("a", "b", F.coalesce("weight", F.lit(0)).alias("weight"))


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, value: str, order: str) -> DataFrame:
    """For each row of ``left`` the last ``value`` of ``right`` at an earlier ``time``: both
    sides in one sequence a key, the value carried forward."""
    both = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.lit(1).alias("__side")).unionByName(
        right.select(*[F.col(c) if c in (key, time, order) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.col(value).alias("__v"), F.lit(0).alias("__side")))
    # rows of one time see only earlier ones: left rows come first
    own = Window.partitionBy(key).orderBy(time, F.desc("__side"), order).rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn(f"last_{value}", F.last("__v", ignorenulls=True).over(own)).where("__side = 1").drop("__v", "__side")


@query("op_asof_prev_event", "SELECT a.event_id, b.event_id AS last_id FROM (SELECT * FROM events WHERE event_type <> 'click') a ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') b ON a.user_id = b.user_id AND a.ts > b.ts")
def op_asof_prev_event(spark, sf_dir):
    """The user's last earlier click of every other event."""
    rows = read_table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    left = rows.where("event_type <> 'click'").select("event_id", "user_id", "ts")
    right = rows.where("event_type = 'click'").select("event_id", "user_id", "ts", F.col("event_id").alias("id"))
    return asof_join(left, right, "user_id", "ts", "id", "event_id").select("event_id", "last_id")


@query("op_interval_events", "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def op_interval_events(spark, sf_dir):
    """Events of a user within ten minutes of each other. Rows meet by user and time bucket,
    each left row in its own bucket and the next, so a busy user is dealt out."""
    rows = read_table(spark, sf_dir, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    width = 600_000_000
    slot = F.floor(F.col("t") / width)
    left = rows.select(F.col("event_id").alias("first"), "user_id", F.col("t").alias("t0"), F.explode(F.array(slot, slot + 1)).alias("slot"))
    right = rows.select(F.col("event_id").alias("second"), "user_id", F.col("t").alias("t1"), slot.alias("slot"))
    return left.join(right, ["user_id", "slot"]).where((F.col("t1") > F.col("t0")) & (F.col("t1") <= F.col("t0") + width)).select("first", "second")


# Aggregations ----------------------------------------------------------------------------
@query("op_group_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT (l_suppkey, l_partkey)) AS pairs, count(*) AS lines FROM lineitem GROUP BY ALL")
def op_group_distinct(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey", "l_partkey").alias("pairs"), F.count("*").alias("lines"))


@query("op_having", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey HAVING count(*) > 620")
def op_having(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n")).where("n > 620")


@query("op_approx_vertices", "SELECT true AS within FROM range(1)")
def op_approx_vertices(spark, sf_dir):
    """Whether the sketch's count of vertices is within a tenth of the exact one."""
    v = fg.ends(Graph.from_edges(graphs.order_part(spark, sf_dir)).edges)
    return v.agg(F.approx_count_distinct("v", 0.03).alias("a"), F.countDistinct("v").alias("n")).select((F.abs(F.col("a") - F.col("n")) <= F.col("n") * 0.1).alias("within"))


for _name, _group in {"rollup": "ROLLUP (level, part)", "cube": "CUBE (level, kind)"}.items():
    _keys = ("level", "part") if _name == "rollup" else ("level", "kind")
    query(f"op_{_name}_kinds", sql.with_(_ST + ", " + _KINDS, f"SELECT {', '.join(_keys)}, grouping({_keys[0]}) * 2 + grouping({_keys[1]}) AS gid, CAST(sum(n) AS BIGINT) AS n FROM kd GROUP BY {_group}"))(
        lambda s, d, name=_name, keys=_keys: getattr(_kinds(s, d), name)(*keys).agg(F.grouping_id().alias("gid"), F.sum("n").alias("n")))


@query("op_grouping_sets", sql.with_(_ST + ", " + _KINDS, "SELECT level, kind, CAST(sum(n) AS BIGINT) AS n FROM kd GROUP BY GROUPING SETS ((level), (kind), ())"))
def op_grouping_sets(spark, sf_dir):
    return _kinds(spark, sf_dir).groupingSets([["level"], ["kind"], []], "level", "kind").agg(F.sum("n").alias("n")).select("level", "kind", "n")


@query("op_pivot_kind", sql.with_(_ST, "SELECT level, CAST(sum(i) AS BIGINT) AS I, CAST(sum(ob) AS BIGINT) AS OB, CAST(sum(eb) AS BIGINT) AS EB FROM st GROUP BY level"))
def op_pivot_kind(spark, sf_dir):
    return _kinds(spark, sf_dir).groupBy("level").pivot("kind", ["I", "OB", "EB"]).agg(F.sum("n"))


@query("op_fingerprint", "SELECT true AS same_xor, true AS same_sum")
def op_fingerprint(spark, sf_dir):
    """The graph's fingerprint against that of its circuit."""
    from tourspark.plans.circuit import circuit

    g = methods.held(spark, sf_dir, "event_trail")
    print_of = lambda df, a, b: df.select(F.xxhash64(F.least(a, b), F.greatest(a, b), "eid").alias("h")).agg(F.expr("bit_xor(h)").alias("x"), F.sum(F.col("h").cast("decimal(38,0)")).alias("s"))
    a, b = print_of(g.edges, "u", "v"), print_of(circuit(g, check=False), "src", "dst").withColumnsRenamed({"x": "x2", "s": "s2"})
    return a.join(F.broadcast(b)).select((F.col("x") == F.col("x2")).alias("same_xor"), (F.col("s") == F.col("s2")).alias("same_sum"))


@query("op_percentiles", sql.with_(sql.edges("order_part"), "SELECT quantile_cont(deg, 0.5) AS p50, quantile_cont(deg, 0.9) AS p90, quantile_cont(deg, 1.0) AS p100 FROM (SELECT count(*) AS deg FROM (SELECT unnest([u, v]) AS v FROM e) GROUP BY v)"))
def op_percentiles(spark, sf_dir):
    deg = fg.degrees(Graph.from_edges(graphs.order_part(spark, sf_dir)))
    return deg.agg(*[F.percentile("deg", p).cast("double").alias(f"p{round(100 * p)}") for p in (0.5, 0.9, 1.0)])


@query("op_percentiles_approx", "SELECT q, true AS within FROM (VALUES (0.5::DOUBLE), (0.9::DOUBLE)) t(q)")
def op_percentiles_approx(spark, sf_dir):
    """q, within: whether the sketch's value has that share of the degrees at or below it and
    no more than that below, but for a thousandth."""
    deg = stage(fg.degrees(Graph.from_edges(graphs.order_part(spark, sf_dir))).select("deg"), "degrees")
    points = (0.5, 0.9)
    found = deg.agg(F.percentile_approx("deg", list(points), 10_000)).first()[0]
    shares = [F.struct(F.lit(q).alias("q"), ((F.avg((F.col("deg") <= x).cast("double")) >= q - 1e-3) & (F.avg((F.col("deg") < x).cast("double")) <= q + 1e-3)).alias("within")) for q, x in zip(points, found, strict=True)]
    return deg.agg(F.array(*shares).alias("s")).select(F.inline("s"))


@query("op_histogram", sql.with_(sql.edges("order_part"), "SELECT count(*) AS vertices, true AS ordered FROM (SELECT DISTINCT unnest([u, v]) AS v FROM e)"))
def op_histogram(spark, sf_dir):
    """vertices, ordered: what the bins of a sketched histogram add up to, and whether they rise."""
    deg = fg.degrees(Graph.from_edges(graphs.order_part(spark, sf_dir)))
    bins = deg.agg(F.histogram_numeric("deg", F.lit(8)).alias("b")).select(F.transform("b", lambda x: x["x"]).alias("x"), F.aggregate("b", F.lit(0.0), lambda a, x: a + x["y"]).alias("n"))
    return bins.select(F.round("n").cast("long").alias("vertices"), (F.col("x") == F.array_sort("x")).alias("ordered"))


# Windows ---------------------------------------------------------------------------------
_HUBS = "hubs AS (SELECT v % 8 AS part, v, deg FROM (SELECT v, count(*) AS deg FROM (SELECT unnest([u, v]) AS v FROM e) GROUP BY v))"


def _hubs(spark, sf_dir):
    return fg.degrees(Graph.from_edges(graphs.supplier_loops(spark, sf_dir))).select((F.col("v") % 8).alias("part"), "v", "deg")


@query("op_rank_hubs", sql.with_(sql.edges("supplier_loops") + ", " + _HUBS, "SELECT part, v, rank() OVER (PARTITION BY part ORDER BY deg DESC) AS r, dense_rank() OVER (PARTITION BY part ORDER BY deg DESC) AS d, ntile(4) OVER (PARTITION BY part ORDER BY deg DESC, v) AS q, round(cume_dist() OVER (PARTITION BY part ORDER BY deg), 9) AS c FROM hubs"))
def op_rank_hubs(spark, sf_dir):
    down = Window.partitionBy("part").orderBy(F.desc("deg"))
    return _hubs(spark, sf_dir).select("part", "v", F.rank().over(down).alias("r"), F.dense_rank().over(down).alias("d"), F.ntile(4).over(Window.partitionBy("part").orderBy(F.desc("deg"), "v")).alias("q"), F.round(F.cume_dist().over(Window.partitionBy("part").orderBy("deg")), 9).alias("c"))


@query("op_topk_per_part", sql.with_(sql.edges("supplier_loops") + ", " + _HUBS, "SELECT part, v, deg FROM (SELECT *, row_number() OVER (PARTITION BY part ORDER BY deg DESC, v) AS r FROM hubs) WHERE r <= 3"))
def op_topk_per_part(spark, sf_dir):
    down = Window.partitionBy("part").orderBy(F.desc("deg"), "v")
    return _hubs(spark, sf_dir).withColumn("r", F.row_number().over(down)).where("r <= 3").drop("r")


@query("op_topk_meta", sql.with_(sql.tree("supplier_loops"), "SELECT a, b, w AS weight FROM m0 ORDER BY w DESC, a, b LIMIT 5"))
def op_topk_meta(spark, sf_dir):
    return metagraph.meta_graph(methods.held(spark, sf_dir, "supplier_loops")).orderBy(F.desc("weight"), "a", "b").limit(5).select("a", "b", "weight")


@query("op_lag_lead_loop", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, last_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_lag_lead_loop(spark, sf_dir):
    own = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = own.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    rows = read_table(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    return rows.select("event_id", F.lag("event_id").over(own).alias("before"), F.lead("event_id").over(own).alias("after"), F.first("event_id").over(own).alias("first"), F.last("event_id").over(whole).alias("last"))


@query("op_running_edges", """SELECT l_suppkey, l_orderkey, l_linenumber, l_partkey, coalesce(CAST(sum(CAST(l_quantity AS BIGINT)) OVER (PARTITION BY l_suppkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT), 0) AS before,
  count(*) OVER (PARTITION BY l_suppkey ORDER BY datediff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)) RANGE BETWEEN 7 PRECEDING AND CURRENT ROW) AS week FROM lineitem""")
def op_running_edges(spark, sf_dir):
    rows = read_table(spark, sf_dir, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_shipdate")
    order = Window.partitionBy("l_suppkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey").rowsBetween(Window.unboundedPreceding, -1)
    days = Window.partitionBy("l_suppkey").orderBy(F.unix_date(F.to_date("l_shipdate"))).rangeBetween(-7, 0)
    return rows.select("l_suppkey", "l_orderkey", "l_linenumber", "l_partkey", F.coalesce(F.sum(F.col("l_quantity").cast("long")).over(order), F.lit(0)).alias("before"), F.count("*").over(days).alias("week"))


@query("op_limit_offset", "SELECT o_orderkey, o_custkey FROM orders ORDER BY o_orderkey LIMIT 20 OFFSET 100")
def op_limit_offset(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").orderBy("o_orderkey").offset(100).limit(20)


# Sets ------------------------------------------------------------------------------------
_HALVES = "a AS (SELECT l_partkey, l_suppkey FROM lineitem WHERE l_orderkey % 3 < 2), b AS (SELECT l_partkey, l_suppkey FROM lineitem WHERE l_orderkey % 3 > 0)"


@query("op_union_intersect_except", f"WITH {_HALVES} SELECT 'union_all' AS op, (SELECT count(*) FROM (FROM a UNION ALL FROM b)) AS n UNION ALL SELECT 'union', (SELECT count(*) FROM (FROM a UNION FROM b)) UNION ALL SELECT 'intersect_all', (SELECT count(*) FROM (FROM a INTERSECT ALL FROM b)) UNION ALL SELECT 'intersect', (SELECT count(*) FROM (FROM a INTERSECT FROM b)) UNION ALL SELECT 'except_all', (SELECT count(*) FROM (FROM a EXCEPT ALL FROM b)) UNION ALL SELECT 'except', (SELECT count(*) FROM (FROM a EXCEPT FROM b))")
def op_union_intersect_except(spark, sf_dir):
    rows = read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    a, b = rows.where("l_orderkey % 3 < 2").drop("l_orderkey"), rows.where("l_orderkey % 3 > 0").drop("l_orderkey")
    made = {"union_all": a.unionByName(b), "union": a.unionByName(b).distinct(), "intersect_all": a.intersectAll(b), "intersect": a.intersect(b), "except_all": a.exceptAll(b), "except": a.subtract(b)}
    out = None
    for name, df in made.items():
        row = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("op"), "n")
        out = row if out is None else out.unionByName(row)
    return out


# Scalars ---------------------------------------------------------------------------------
@query("op_string_tokens", "SELECT w, count(*) AS n FROM (SELECT unnest(list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: length(x) > 3)) AS w FROM documents) GROUP BY w")
def op_string_tokens(spark, sf_dir):
    words = F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: F.length(w) > 3)
    return read_table(spark, sf_dir, "documents").select(F.explode(words).alias("w")).groupBy("w").agg(F.count("*").alias("n"))


@query("op_url_host_links", "SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*) AS pages, CAST(sum(len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))) AS BIGINT) AS links FROM pages GROUP BY host")
def op_url_host_links(spark, sf_dir):
    rows = read_table(spark, sf_dir, "pages").select(F.parse_url("url", F.lit("HOST")).alias("host"), F.size(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("k"))
    return rows.groupBy("host").agg(F.count("*").alias("pages"), F.sum("k").alias("links"))


@query("op_dates", "SELECT strftime(date_trunc('week', ts), '%Y-%m-%d') AS week, CAST(date_part('hour', ts) AS INTEGER) AS hour, count(*) AS n, CAST(max(date_diff('day', TIMESTAMP '2024-01-01', ts)) AS INTEGER) AS days FROM events GROUP BY ALL")
def op_dates(spark, sf_dir):
    rows = read_table(spark, sf_dir, "events").select("ts")
    return rows.groupBy(F.date_format(F.date_trunc("week", "ts"), "yyyy-MM-dd").alias("week"), F.hour("ts").alias("hour")).agg(F.count("*").alias("n"), F.max(F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date"))).alias("days"))


@query("op_arrays", "SELECT label, count(*) AS n, CAST(sum(CAST(round(1000 * sqrt(list_dot_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[])))) AS BIGINT)) AS BIGINT) AS norms, CAST(sum(len(embedding[1:8])) AS BIGINT) AS sliced FROM embeddings GROUP BY label")
def op_arrays(spark, sf_dir):
    e = F.col("embedding").cast("array<double>")
    dot = F.aggregate(F.zip_with(e, e, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    rows = read_table(spark, sf_dir, "embeddings").select("label", F.round(1000 * F.sqrt(dot)).cast("long").alias("norm"), F.size(F.slice(e, 1, 8)).alias("k"))
    return rows.groupBy("label").agg(F.count("*").alias("n"), F.sum("norm").alias("norms"), F.sum("k").alias("sliced"))


@query("op_maps", sql.with_(_ST, "SELECT level, part, i + ob AS i_ob, eb FROM st"))
def op_maps(spark, sf_dir):
    s = _stats(spark, sf_dir)
    a, b = F.map_from_arrays(F.array(F.lit("x")), F.array("i")), F.map_from_entries(F.array(F.struct(F.lit("x").alias("k"), F.col("ob").alias("v")), F.struct(F.lit("y").alias("k"), F.col("eb").alias("v"))))
    both = F.map_zip_with(a, b, lambda k, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))
    return s.select("level", "part", F.element_at(both, "x").alias("i_ob"), F.element_at(both, "y").alias("eb"))


@query("op_json", "SELECT event_type, count(*) AS n, count(DISTINCT json_keys(props)) AS shapes FROM events GROUP BY event_type")
def op_json(spark, sf_dir):
    rows = read_table(spark, sf_dir, "events").select("event_type", F.json_object_keys("props").alias("keys"))
    return rows.groupBy("event_type").agg(F.count("*").alias("n"), F.countDistinct("keys").alias("shapes"))


@query("op_recursive_reach", "WITH RECURSIVE r AS (SELECT r_regionkey AS root, 0 AS depth, CAST(r_name AS VARCHAR) AS name FROM region UNION ALL SELECT root, 1, n_name FROM r JOIN nation ON n_regionkey = root AND depth = 0) SELECT root, depth, count(*) AS n FROM r GROUP BY ALL")
def op_recursive_reach(spark, sf_dir):
    for t in ("region", "nation"):
        read_table(spark, sf_dir, t).createOrReplaceTempView(f"tourspark_{t}")
    return spark.sql("""
        WITH RECURSIVE reached (root, depth) AS (
          SELECT r_regionkey, 0 FROM tourspark_region
          UNION ALL SELECT n_regionkey, depth + 1 FROM reached JOIN tourspark_nation ON n_regionkey = root WHERE depth < 1
        ) SELECT root, depth, count(*) AS n FROM reached GROUP BY root, depth""")


@query("op_lateral_best_pair", sql.with_(sql.tree("supplier_loops"), "SELECT p0.leaf AS part, x.other, x.w AS weight FROM p0, LATERAL (SELECT CASE WHEN a = p0.leaf THEN b ELSE a END AS other, w FROM m0 WHERE a = p0.leaf OR b = p0.leaf ORDER BY w DESC, a, b LIMIT 1) x"))
def op_lateral_best_pair(spark, sf_dir):
    """Every part's heaviest neighbour."""
    meta = metagraph.meta_graph(methods.held(spark, sf_dir, "supplier_loops"))
    sides = meta.select(F.explode(F.array(F.struct(F.col("a").alias("p"), F.col("b").alias("o")), F.struct(F.col("b").alias("p"), F.col("a").alias("o")))).alias("s"), "a", "b", "weight")
    best = sides.groupBy(F.col("s.p").alias("part")).agg(F.max_by("s.o", F.struct("weight", -F.col("a"), -F.col("b"))).alias("other"), F.max("weight").alias("weight"))
    return best


@query("op_exists_scalar_subquery", "SELECT o_orderkey, (SELECT count(*) FROM lineitem WHERE l_orderkey = o_orderkey) AS lines FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 49)")
def op_exists_scalar_subquery(spark, sf_dir):
    for t in ("orders", "lineitem"):
        read_table(spark, sf_dir, t).createOrReplaceTempView(f"tourspark_{t}")
    return spark.sql("""
        SELECT o_orderkey, (SELECT count(*) FROM tourspark_lineitem WHERE l_orderkey = o_orderkey) AS lines FROM tourspark_orders
        WHERE EXISTS (SELECT 1 FROM tourspark_lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 49)""")


@query("op_labels_join_quality", "SELECT lang, count(*) AS n, CAST(sum(CASE WHEN quality = 1 THEN 1 WHEN quality = 0 THEN -1 ELSE 0 END) AS BIGINT) AS balance FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def op_labels_join_quality(spark, sf_dir):
    rows = read_table(spark, sf_dir, "documents").select("doc_id", "lang").join(read_table(spark, sf_dir, "labels"), "doc_id")
    return rows.groupBy("lang").agg(F.count("*").alias("n"), F.sum(F.when(F.col("quality") == 1, 1).when(F.col("quality") == 0, -1).otherwise(0)).alias("balance"))


@query("op_dialog_edges", "SELECT role, t AS next_role, count(*) AS n FROM (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS t FROM conversations) WHERE t IS NOT NULL GROUP BY ALL")
def op_dialog_edges(spark, sf_dir):
    own = Window.partitionBy("conv_id").orderBy("turn")
    return read_table(spark, sf_dir, "conversations").select("role", F.lead("role").over(own).alias("next_role")).where("next_role is not null").groupBy("role", "next_role").agg(F.count("*").alias("n"))


_GRAMS = "(SELECT {0} AS id, list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) AS g FROM (SELECT {0}, list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: x <> '') AS w FROM {1}) WHERE len(w) >= 3)"


@query("op_benchmark_overlap", f"SELECT b.id AS item_id, count(DISTINCT d.id) AS docs FROM (SELECT id, unnest(g) AS g FROM {_GRAMS.format('item_id', 'benchmark')}) b JOIN (SELECT id, unnest(g) AS g FROM {_GRAMS.format('doc_id', 'documents')}) d USING (g) GROUP BY b.id")
def op_benchmark_overlap(spark, sf_dir):
    """Documents that share a run of three words with each benchmark item."""
    def grams(table, key):
        words = F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: w != "")
        rows = read_table(spark, sf_dir, table).select(key, words.alias("w")).where(F.size("w") >= 3)
        return rows.select(key, F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 2), lambda i: F.xxhash64(F.slice("w", i, 3))))).alias("g"))

    # a common run is dealt over cells by document, and meets a copy of its items in each
    cells = 16
    items = grams("benchmark", "item_id").withColumn("cell", F.explode(F.sequence(F.lit(0), F.lit(cells - 1))))
    docs = grams("documents", "doc_id").withColumn("cell", F.pmod(F.xxhash64("doc_id"), F.lit(cells)).cast("int"))
    return items.join(docs, ["g", "cell"]).groupBy("item_id").agg(F.countDistinct("doc_id").alias("docs"))


# Sinks and user-defined functions --------------------------------------------------------
_TRAIL = sql.cover("event_trail")


def _round_trip(kind: str):
    def run(spark, sf_dir):
        from tourspark.sources import readers

        g = methods.held(spark, sf_dir, "event_trail")
        path = stage_path(spark, f"sink-{kind}")
        readers.write_edges(g.edges, path, kind)
        back = readers.read_edges(spark, path, kind)
        return back.groupBy("u", "v").agg(F.count("*").alias("n"))

    return run


for _kind in ("csv", "tsv", "json", "parquet", "adjacency"):
    query(f"op_{_kind}_roundtrip", _TRAIL)(_round_trip(_kind))


@query("op_bucketed_table", _TRAIL)
def op_bucketed_table(spark, sf_dir):
    from tourspark.sources import readers

    name = readers.save_bucketed(methods.held(spark, sf_dir, "event_trail").edges, "tourspark_trail", "u", 8)
    return spark.table(name).groupBy("u", "v").agg(F.count("*").alias("n"))


@query("op_udf_pandas", sql.with_(sql.edges("event_trail"), "SELECT u, v, u * 31 + v AS mark, count(*) AS n FROM e GROUP BY ALL"))
def op_udf_pandas(spark, sf_dir):
    from tourspark.functions import sqlapi

    g = methods.held(spark, sf_dir, "event_trail")
    return g.edges.withColumn("mark", sqlapi.edge_mark("u", "v")).groupBy("u", "v", "mark").agg(F.count("*").alias("n"))


@query("op_udaf_checksum", sql.with_(sql.edges("event_trail"), "SELECT u, CAST(sum(v) % 1000003 AS BIGINT) AS mark FROM e GROUP BY u"))
def op_udaf_checksum(spark, sf_dir):
    from tourspark.functions import sqlapi

    return methods.held(spark, sf_dir, "event_trail").edges.groupBy("u").agg(sqlapi.walk_checksum("v").alias("mark"))


@query("op_udtf_circuit", sql.audit("geo_doubled"))
def op_udtf_circuit(spark, sf_dir):
    from tourspark.functions import sqlapi
    from tourspark.plans import components, verify
    from tourspark.session import stage

    g = methods.held(spark, sf_dir, "geo_doubled")
    sqlapi.register(spark)
    g.edges.join(components.components(g).withColumnRenamed("v", "u"), "u").select("comp", "eid", "u", "v").createOrReplaceTempView("tourspark_edges")
    return verify.audit(g, stage(spark.sql("SELECT comp, pos, eid, src, dst FROM circuit_of(TABLE(tourspark_edges) PARTITION BY comp)"), "udtf"))


@query("op_udtf_merge_tree", methods._tree_sql("supplier_loops"))
def op_udtf_merge_tree(spark, sf_dir):
    from tourspark.functions import sqlapi

    sqlapi.register(spark)
    metagraph.meta_graph(methods.held(spark, sf_dir, "supplier_loops")).createOrReplaceTempView("tourspark_meta")
    return spark.sql("SELECT level, child_a, child_b, parent, weight FROM merge_tree_of(TABLE(SELECT a, b, weight FROM tourspark_meta) WITH SINGLE PARTITION)")


@query("op_sql_is_even", sql.with_(sql.edges("event_trail"), "SELECT true AS even, count(*) AS n FROM (SELECT DISTINCT unnest([u, v]) AS v FROM e)"))
def op_sql_is_even(spark, sf_dir):
    from tourspark.functions import sqlapi

    sqlapi.register(spark)
    fg.degrees(methods.held(spark, sf_dir, "event_trail")).createOrReplaceTempView("tourspark_degrees")
    return spark.sql("SELECT is_even_degree(deg) AS even, count(*) AS n FROM tourspark_degrees GROUP BY 1")


@query("op_sql_join_level", sql.with_(sql.levels("event_trail"), "SELECT jl, count(*) AS n FROM j GROUP BY jl"))
def op_sql_join_level(spark, sf_dir):
    from tourspark.functions import sqlapi

    sqlapi.register(spark)
    g = methods.held(spark, sf_dir, "event_trail")
    tree = methods.tree_of(g)
    paths = {p: [m[p] for m in tree.maps()] for p in tree.parts}
    rows = spark.createDataFrame([(p, x) for p, x in paths.items()], "part int, path array<int>")
    rows.createOrReplaceTempView("tourspark_paths")
    fg.split_edges(g).createOrReplaceTempView("tourspark_split")
    return spark.sql("""SELECT join_level(a.path, b.path) AS jl, count(*) AS n FROM tourspark_split
        JOIN tourspark_paths a ON pu = a.part JOIN tourspark_paths b ON pv = b.part GROUP BY 1""")


@query("op_datasource_torus", sql.with_("g AS (SELECT i AS u, unnest([i // 24 * 24 + (i + 1) % 24, (i + 24) % 168]) AS v FROM range(168) t(i)), w AS (SELECT dayofweek(ts) * 24 + hour(ts) AS k, count(*) AS n FROM events GROUP BY k)", "SELECT least(u, v) AS u, greatest(u, v) AS v, CAST(sum(n) AS BIGINT) AS n FROM g JOIN w ON k = u GROUP BY ALL"))
def op_datasource_torus(spark, sf_dir):
    """The torus of weekdays (Sunday is 0) and hours: each event of a cell takes the cell's
    edges to the next hour and the next day."""
    from tourspark.sources import generators

    generators.register(spark)
    cell = ((F.dayofweek("ts") - 1) * 24 + F.hour("ts")).cast("long").alias("k")
    weight = read_table(spark, sf_dir, "events").groupBy(cell).agg(F.count("*").alias("n"))
    rows = spark.read.format("torus").option("rows", 7).option("cols", 24).load().join(weight, F.col("u") == F.col("k"))
    return rows.groupBy(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).agg(F.sum("n").alias("n"))


@query("op_datasource_rmat", sql.with_(f"g AS ({sql.PAIRS['rmat']}), w AS (SELECT o_custkey % 1024 AS k, count(*) AS n FROM orders GROUP BY k)", "SELECT least(u, v) AS u, greatest(u, v) AS v, CAST(sum(n) AS BIGINT) AS n FROM g JOIN w ON k = u GROUP BY ALL"))
def op_datasource_rmat(spark, sf_dir):
    """The power-law graph over customers in 1,024 groups: each order of a group takes every
    edge that the source draws from it."""
    from tourspark.sources import generators

    generators.register(spark)
    weight = read_table(spark, sf_dir, "orders").groupBy((F.col("o_custkey") % 1024).alias("k")).agg(F.count("*").alias("n"))
    rows = spark.read.format("rmat").option("scale", 10).load().join(weight, F.col("u") == F.col("k"))
    return rows.groupBy(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).agg(F.sum("n").alias("n"))


# Extensions ------------------------------------------------------------------------------
@query("open_trail_edges", sql.with_(sql.edges("worked"), "SELECT count(*) - 1 AS n_edges, true AS chained, CAST(1 AS BIGINT) AS low, CAST(2 AS BIGINT) AS high FROM e"))
def open_trail_edges(spark, sf_dir):
    """The sample graph without the edge 1-2: an open trail between 1 and 2."""
    from tourspark.plans import extensions

    g = graphs.worked_example(spark)
    cut = Graph(g.edges.where("NOT (u = 1 AND v = 2)"), g.vertices, g.n_parts)
    return extensions.trail_summary(extensions.open_trail(cut))


@query("covering_walk_geo", "SELECT true AS closed, true AS covers")
def covering_walk_geo(spark, sf_dir):
    """The geographic trees, most of whose vertices are leaves of a hub: all odd, all paired."""
    from tourspark.plans import extensions

    g = Graph.from_edges(graphs.geo_tree(spark, sf_dir))
    g = g.map_edges(stage(g.edges, "geo"))
    walk, extra = extensions.covering_walk(g)
    return extensions.cover_summary(g, walk, extra).select("closed", "covers")


@query("covering_walk_summary", sql.with_(sql.edges("worked"), "SELECT true AS closed, true AS covers, 1 AS extra FROM range(1)"))
def covering_walk_summary(spark, sf_dir):
    """The sample graph with the edge 1-2 twice: the cheapest walk takes it once more."""
    from tourspark.plans import extensions

    base = graphs.worked_example(spark)
    more = spark.createDataFrame([(1, 2)], "u long, v long")
    g = Graph.from_edges(base.edges.select("u", "v").unionByName(more))
    walk, extra = extensions.covering_walk(g)
    return extensions.cover_summary(g, walk, extra)


