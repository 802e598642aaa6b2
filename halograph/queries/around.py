"""Operators, sources, sinks, streams and user functions around the methods."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from halograph import streaming
from halograph.catalog import query
from halograph.functions.ring import whole
from halograph.graph import halo, neighbors
from halograph.graph.scratch import Scratch
from halograph.operators import relational, udx
from halograph.queries.graphs import BASE, BOND, PARTED, buckets, quartz_bonds
from halograph.sources import sinks, systems, tables, xyz
from halograph.twins import sql as q

read = tables.read


@query("op_scan", "SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_quantity >= 49 AND l_returnflag = 'R'")
def scan(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").filter("l_quantity >= 49 AND l_returnflag = 'R'").select("l_orderkey", "l_partkey", "l_quantity")


@query("op_roundtrip", q.select(PARTED, "SELECT part_id, count(*) AS edges, CAST(sum(d2) AS BIGINT) AS total FROM owned GROUP BY part_id"))
def roundtrip(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    path = Scratch(spark).root
    sinks.by_part(halo.owned_edges(e, a), f"{path}/parts")
    return spark.read.parquet(f"{path}/parts").groupBy("part_id").agg(F.count(F.lit(1)).alias("edges"), F.sum("d2").alias("total"))


@query("op_text_system", q.select(q.lattice(), "SELECT atom_id, species, x, y, z FROM atoms"))
def text_system(spark, sf_dir):
    path = f"{Scratch(spark).root}/particles"
    xyz.write(systems.lattice(spark, sf_dir), path)
    return xyz.read_rows(spark, path)


_MI = lambda a: f"CASE WHEN 2 * ({a} - 5000) > l{a} THEN {a} - 5000 - l{a} WHEN 2 * ({a} - 5000) < -l{a} THEN {a} - 5000 + l{a} ELSE {a} - 5000 END"


@query("op_filter_project", q.select(q.quartz(), f"SELECT atom_id, {_MI('x')} AS dx, {_MI('y')} AS dy FROM atoms, cell WHERE species = 14"))
def filter_project(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    m = lambda a, k: relational.minimum_image(F.col(a) - 5000, s.cell.lengths[k])
    return s.atoms.where("species = 14").select("atom_id", m("x", 0).alias("dx"), m("y", 1).alias("dy"))


@query("op_join_hints", "SELECT n_name, CAST(count(*) AS BIGINT) AS customers, hint FROM customer JOIN nation ON c_nationkey = n_nationkey, (VALUES ('broadcast'), ('merge'), ('shuffle_hash')) h(hint) GROUP BY n_name, hint")
def join_hints(spark, sf_dir):
    c, n = read(spark, sf_dir, "customer"), read(spark, sf_dir, "nation")
    out = None
    for hint in ("broadcast", "merge", "shuffle_hash"):
        row = c.join(n.hint(hint), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers")).withColumn("hint", F.lit(hint))
        out = row if out is None else out.union(row)
    return out


@query("op_join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey")
def join_theta(spark, sf_dir):
    n = read(spark, sf_dir, "nation")  # 25 rows
    a, b = n.select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("ra")), n.select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("rb"))
    return a.join(F.broadcast(b), F.col("ra") < F.col("rb")).select("a", "b")


@query("op_join_range", "SELECT p_partkey, b.i AS box FROM part JOIN (SELECT i, i * 150 AS low, i * 150 + 300 AS high FROM range(20) r(i)) b ON floor(p_retailprice) >= low AND floor(p_retailprice) < high")
def join_range(spark, sf_dir):
    points = read(spark, sf_dir, "part").select("p_partkey", F.floor("p_retailprice").alias("v"))
    boxes = spark.range(20).select(F.col("id").alias("box"), (F.col("id") * 150).alias("low"), (F.col("id") * 150 + 300).alias("high"))
    return relational.range_join(points, boxes, "v", "low", "high", 150).select("p_partkey", "box")


@query("op_join_asof", "SELECT c.user_id, c.event_id, (SELECT v.event_id FROM events v WHERE v.event_type = 'view' AND v.user_id = c.user_id AND v.ts <= c.ts ORDER BY v.ts DESC, v.event_id DESC LIMIT 1) AS last_view FROM events c WHERE c.event_type = 'purchase'")
def join_asof(spark, sf_dir):
    e = read(spark, sf_dir, "events")
    buys = e.filter("event_type = 'purchase'").select("user_id", "ts", "event_id")
    views = e.filter("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("last_view"))
    # identifiers break ties of time on both sides
    a = buys.select("user_id", "ts", F.lit(None).cast("long").alias("last_view"), F.lit(1).alias("side"), "event_id")
    b = views.select("user_id", "ts", "last_view", F.lit(0).alias("side"), F.col("last_view").alias("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", "side", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn("last_view", F.last("last_view", ignorenulls=True).over(w)).filter("side = 1").select("user_id", "event_id", "last_view")


@query("op_semi_anti", "SELECT CAST((SELECT count(*) FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)) AS BIGINT) AS with_orders, CAST((SELECT count(*) FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)) AS BIGINT) AS without")
def semi_anti(spark, sf_dir):
    c = read(spark, sf_dir, "customer").select("c_custkey")
    o = read(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey"))
    n = F.count(F.lit(1))
    return c.join(o, "c_custkey", "left_semi").agg(n.alias("with_orders")).crossJoin(c.join(o, "c_custkey", "left_anti").agg(n.alias("without")))


@query("op_lateral_topk", q.select(BASE, "SELECT dst, src, d2, rank FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY d2, src, ix, iy, iz) AS rank FROM edges) WHERE rank <= 3"))
def lateral_topk(spark, sf_dir):
    return relational.nearest(quartz_bonds(spark, sf_dir)[1], 3).select("dst", "src", "d2", F.col("rank").cast("long").alias("rank"))


@query("op_agg", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_partkey) AS BIGINT) AS keys, CAST(max(l_orderkey) AS BIGINT) AS most FROM lineitem GROUP BY l_returnflag, l_linestatus")
def agg(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_partkey").alias("keys"), F.max("l_orderkey").alias("most"))


@query("op_agg_salted", "SELECT l_returnflag, CAST(sum(l_suppkey) AS BIGINT) AS l_suppkey FROM lineitem GROUP BY l_returnflag")
def agg_salted(spark, sf_dir):
    return relational.salted_sum(read(spark, sf_dir, "lineitem").select("l_returnflag", "l_suppkey", "l_orderkey"), "l_returnflag", "l_suppkey")


@query("op_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT (l_partkey, l_suppkey)) AS pairs FROM lineitem")
def distinct(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_partkey", "l_suppkey").alias("pairs"))


@query("op_distinct_approx")  # sketches: rows only
def distinct_approx(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_extendedprice", 0.5).alias("median_price"))


@query("op_cube", q.select(PARTED + q.buckets(), "SELECT part_id, kind, count(*) AS n, CAST(grouping(part_id) * 2 + grouping(kind) AS BIGINT) AS level FROM buckets GROUP BY CUBE (part_id, kind)"))
def cube(spark, sf_dir):
    cubed = buckets(spark, sf_dir).cube("part_id", "kind").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))
    # Spark leaves out the grand total of no rows.
    total = spark.range(1).select(F.lit(3).cast("long").alias("level"))
    return cubed.join(total.hint("merge"), "level", "full_outer").select("part_id", "kind", F.coalesce("n", F.lit(0)).alias("n"), "level")


@query("op_rollup", "SELECT n_regionkey, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)")
def rollup(spark, sf_dir):
    c, n = read(spark, sf_dir, "customer"), read(spark, sf_dir, "nation")
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).rollup("n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("op_pivot", q.select(PARTED + q.buckets(), "SELECT part_id, count(*) FILTER (kind = 'PURE') AS pure, count(*) FILTER (kind = 'TO') AS sent, count(*) FILTER (kind = 'FROM') AS received FROM buckets GROUP BY part_id"))
def pivot(spark, sf_dir):
    wide = buckets(spark, sf_dir).groupBy("part_id").pivot("kind", ["PURE", "TO", "FROM"]).agg(F.count(F.lit(1))).na.fill(0)
    return wide.select("part_id", F.col("PURE").alias("pure"), F.col("TO").alias("sent"), F.col("FROM").alias("received"))


@query("op_unpivot", "SELECT n_nationkey, 'region' AS what, n_regionkey AS v FROM nation UNION ALL SELECT n_nationkey, 'key', n_nationkey FROM nation")
def unpivot(spark, sf_dir):
    n = read(spark, sf_dir, "nation").select("n_nationkey", F.col("n_regionkey").alias("region"), F.col("n_nationkey").alias("key"))
    return n.unpivot("n_nationkey", ["region", "key"], "what", "v")


@query("op_window_rank", "SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment, c_custkey) AS n FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
def window_rank(spark, sf_dir):
    w = Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    u = Window.partitionBy("c_nationkey").orderBy("c_mktsegment", "c_custkey")
    rows = read(spark, sf_dir, "customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.row_number().over(u).alias("n"))
    return rows.select("c_custkey", *[F.col(c).cast("long").alias(c) for c in ("r", "dr", "n")])


@query("op_window_frame", "SELECT event_id, CAST(sum(event_id) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS last3, lag(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS before, first_value(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS first FROM events")
def window_frame(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return read(spark, sf_dir, "events").select("event_id", F.sum("event_id").over(w.rowsBetween(-2, 0)).alias("last3"), F.lag("event_id").over(w).alias("before"), F.first("event_id").over(w).alias("first"))


@query("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def topk(spark, sf_dir):
    return read(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("op_setops", "SELECT 'both' AS what, count(*) AS n FROM (SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL SELECT 'only_customers', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT SELECT s_nationkey FROM supplier) UNION ALL SELECT 'either', count(*) FROM (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier)")
def setops(spark, sf_dir):
    a, b = read(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), read(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    n = lambda df, what: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(what).alias("what"), "n")
    return n(a.intersect(b), "both").union(n(a.subtract(b), "only_customers")).union(n(a.union(b).distinct(), "either"))


@query("op_scalar_math", "SELECT p_partkey, p_size // 7 AS q, p_size % 7 AS r, CAST(floor(sqrt(p_size)) AS BIGINT) AS root FROM part")
def scalar_math(spark, sf_dir):
    s = F.col("p_size")
    return read(spark, sf_dir, "part").select("p_partkey", F.call_function("div", s, F.lit(7)).alias("q"), (s % 7).alias("r"), F.floor(F.sqrt(s)).alias("root"))


@query("op_scalar_text", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, upper(substr(url, 1, 4)) AS scheme, CAST(length(url) AS INT) AS n FROM pages")
def scalar_text(spark, sf_dir):
    u = F.col("url")
    return read(spark, sf_dir, "pages").select("page_id", F.regexp_extract(u, r"^[a-z]+://([^/]+)", 1).alias("host"), F.upper(F.substring(u, 1, 4)).alias("scheme"), F.char_length(u).alias("n"))


@query("op_scalar_date", "SELECT o_orderkey, CAST(date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS INT) AS days, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m FROM orders")
def scalar_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return read(spark, sf_dir, "orders").select("o_orderkey", F.datediff(d.cast("date"), F.lit("1995-01-01").cast("date")).alias("days"), F.year(d).alias("y"), F.month(d).alias("m"))


@query("op_scalar_json", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def scalar_json(spark, sf_dir):
    return read(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@query("op_array", "SELECT vec_id, CAST(list_sum(list_transform(embedding[1:8], lambda x: CAST(floor(CAST(x AS DOUBLE) * 1000) AS BIGINT))) AS BIGINT) AS s, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive FROM embeddings")
def array(spark, sf_dir):
    e = F.col("embedding")
    scaled = F.transform(F.slice(e, 1, 8), lambda x: F.floor(x.cast("double") * 1000))
    return read(spark, sf_dir, "embeddings").select("vec_id", F.aggregate(scaled, F.lit(0).cast("long"), lambda a, x: a + x).alias("s"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"))


@query("op_map", "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type HAVING count(*) > 1")
def map_(spark, sf_dir):
    per = read(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    held = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return held.select("user_id", F.explode(F.map_filter("m", lambda k, v: v > 1)).alias("event_type", "n"))


@query("op_khop", q.select(q.successor(), "SELECT hop, count(*) AS nodes FROM (SELECT 0 AS hop, 7 AS n UNION SELECT DISTINCT 1, dst FROM edges WHERE src = 7 UNION SELECT DISTINCT 2, b.dst FROM edges a JOIN edges b ON b.src = a.dst WHERE a.src = 7) GROUP BY hop"))
def khop(spark, sf_dir):
    e = systems.successor(spark, sf_dir).edges.select("src", "dst")
    at = spark.range(1).select(F.lit(7).cast("long").alias("n"))
    out = at.select(F.lit(0).alias("hop"), "n")
    for hop in (1, 2):
        at = e.join(F.broadcast(at) if hop == 1 else at, e.src == F.col("n")).select(F.col("dst").alias("n")).distinct()
        out = out.union(at.select(F.lit(hop), "n"))
    return out.groupBy("hop").agg(F.count(F.lit(1)).alias("nodes"))


_DOUBLED = "WITH RECURSIVE r(start, n) AS (SELECT DISTINCT p_size, p_size FROM {part} UNION ALL SELECT start, n * 2 FROM r WHERE n > 0 AND n < 512) SELECT p_partkey, n FROM {part} JOIN r ON p_size = start"


@query("op_recursive", _DOUBLED.replace("{part}", "part"))
def recursive(spark, sf_dir):
    """The size of every part and its doublings; the recursion runs over the distinct sizes, so it stays small at any number of parts."""
    return spark.sql(_DOUBLED, part=read(spark, sf_dir, "part"))


@query("op_sample", "SELECT o_orderkey FROM orders WHERE o_orderkey % 10 = 0")
def sample(spark, sf_dir):
    """A fixed sample: every tenth key (a sampling operator, whose feature is the share)."""
    return read(spark, sf_dir, "orders").filter(F.pmod("o_orderkey", F.lit(10)) == 0).select("o_orderkey")


@query("op_sample_degree")  # random: rows only
def sample_degree(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return neighbors.estimated_degree(s.atoms, s.cell, BOND)


@query("op_udf", q.select(q.quartz() + q.edges(BOND), f"SELECT src, dst, ix, iy, iz, CAST(round((1 - d2 / {BOND * BOND}.0) * (1 - d2 / {BOND * BOND}.0) * (1 + 2 * d2 / {BOND * BOND}.0) * 1000) AS BIGINT) AS e FROM edges"))
def udf(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    e = neighbors.neighbor_list(s.atoms, s.cell, BOND)
    return e.select(*neighbors.EDGE_KEY, F.round(udx.envelope(F.col("d2").cast("double"), F.lit(float(BOND))) * 1000).cast("long").alias("e"))


@query("op_udaf", "SELECT event_type, CAST(round(sqrt(avg(value * value)) * 1000) AS BIGINT) AS rms FROM events WHERE value IS NOT NULL GROUP BY event_type")
def udaf(spark, sf_dir):
    return read(spark, sf_dir, "events").filter("value IS NOT NULL").groupBy("event_type").agg(F.round(udx.root_mean_square("value") * 1000).cast("long").alias("rms"))


_BINS = [("bins", "SELECT x // 10000 AS bx, y // 10000 AS by_, z // 10000 AS bz, count(*) AS n FROM atoms GROUP BY ALL")]
_OFFSET = "(VALUES (-1), (0), (1))"


@query("op_udtf", q.select(q.lattice() + _BINS, f"SELECT bx, by_, bz, n, a.i AS ox, b.i AS oy, c.i AS oz FROM bins, {_OFFSET} a(i), {_OFFSET} b(i), {_OFFSET} c(i)"))
def udtf(spark, sf_dir):
    """The 27 bins around every occupied bin of the lattice of parts, with the atoms of the bin."""
    udx.register(spark)
    at = [whole(F.col(a), 10_000).alias(b) for a, b in (("x", "bx"), ("y", "by_"), ("z", "bz"))]
    bins = systems.lattice(spark, sf_dir).atoms.groupBy(*at).agg(F.count(F.lit(1)).alias("n"))
    return spark.sql("SELECT b.*, o.ox, o.oy, o.oz FROM {bins} b, LATERAL neighbor_bins(1) o", bins=bins)


@query("op_sql", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_regionkey = 1 GROUP BY n_name")
def sql(spark, sf_dir):
    """The SQL surface: tables as parameters, values by name."""
    return spark.sql(
        "SELECT n_name, count(*) AS n FROM {customer} JOIN {nation} ON c_nationkey = n_nationkey WHERE n_regionkey = :region GROUP BY n_name",
        args={"region": 1}, customer=read(spark, sf_dir, "customer"), nation=read(spark, sf_dir, "nation"),
    )


@query("op_sql_function", q.select(q.quartz(), f"SELECT atom_id, {_MI('x')} AS dx FROM atoms, cell"))
def sql_function(spark, sf_dir):
    udx.register(spark)
    s = systems.quartz(spark, sf_dir)
    return s.atoms.select("atom_id", F.expr(f"min_image(x - 5000, {s.cell.lengths[0]})").alias("dx"))


EPOCH = "epoch(ts)"


@query("trajectory_frames", f"SELECT CAST(floor({EPOCH} / 3600) * 3600 AS BIGINT) AS frame_start, event_type, count(*) AS events, max(user_id) AS most_user FROM events GROUP BY ALL")
def trajectory_frames(spark, sf_dir):
    """Tumbling frames of the event stream; everything there is read, so all frames are complete."""
    stream = streaming.event_stream(spark, f"{sf_dir}/events.parquet")
    return streaming.run_batches(streaming.tumbling_frames(stream), Scratch(spark).root, "complete").drop("batch")


@query("trajectory_sliding", f"SELECT CAST(s AS BIGINT) AS frame_start, count(*) AS events FROM (SELECT unnest([floor({EPOCH} / 3600) * 3600, floor({EPOCH} / 3600) * 3600 - 3600]) AS s FROM events) GROUP BY s")
def trajectory_sliding(spark, sf_dir):
    stream = streaming.event_stream(spark, f"{sf_dir}/events.parquet")
    return streaming.run_batches(streaming.sliding_frames(stream), Scratch(spark).root, "complete").drop("batch")


@query(
    "trajectory_sessions",
    f"WITH c AS (SELECT *, CASE WHEN {EPOCH} - lag({EPOCH}) OVER w < 21600 THEN 0 ELSE 1 END AS cut FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM c) SELECT user_id, count(*) AS events, CAST(floor(min({EPOCH})) AS BIGINT) AS first FROM s GROUP BY user_id, session",
)
def trajectory_sessions(spark, sf_dir):
    stream = streaming.event_stream(spark, f"{sf_dir}/events.parquet")
    out = streaming.run_batches(streaming.session_frames(stream, "6 hours"), Scratch(spark).root, "complete")
    return out.select("user_id", "events", "first")


@query("trajectory_dedup", "SELECT count(*) AS events, count(DISTINCT event_id) AS ids FROM events")
def trajectory_dedup(spark, sf_dir):
    stream = streaming.without_repeats(streaming.event_stream(spark, f"{sf_dir}/events.parquet")).select("event_id", "user_id")
    return streaming.run_available(stream, Scratch(spark).root).agg(F.count(F.lit(1)).alias("events"), F.countDistinct("event_id").alias("ids"))


@query("trajectory_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def trajectory_static(spark, sf_dir):
    users = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    stream = streaming.with_users(streaming.event_stream(spark, f"{sf_dir}/events.parquet"), users).select("event_id", "c_mktsegment")
    return streaming.run_available(stream, Scratch(spark).root)


@query("trajectory_interval_join", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTES")
def trajectory_interval(spark, sf_dir):
    one = lambda kind: streaming.event_stream(spark, f"{sf_dir}/events.parquet").filter(F.col("event_type") == kind)
    return streaming.run_available(streaming.within(one("view"), one("purchase"), 60).select("a_id", "b_id"), Scratch(spark).root)


_TRACKED = """WITH RECURSIVE n AS (
  SELECT user_id, abs(coalesce(value, 0)) AS v, row_number() OVER (PARTITION BY user_id ORDER BY event_id) AS i FROM events),
walk AS (
  SELECT user_id, i, CASE WHEN v > 100 THEN CAST(0 AS DOUBLE) ELSE v END AS total, CASE WHEN v > 100 THEN 1 ELSE 0 END AS rebuild FROM n WHERE i = 1
  UNION ALL SELECT w.user_id, n.i, CASE WHEN total + v > 100 THEN CAST(0 AS DOUBLE) ELSE total + v END, CASE WHEN total + v > 100 THEN rebuild + 1 ELSE rebuild END
  FROM walk w JOIN n ON n.user_id = w.user_id AND n.i = w.i + 1)
SELECT user_id, CAST(r AS INT) AS rebuild FROM (SELECT user_id, max(rebuild) AS most FROM walk GROUP BY user_id), generate_series(1, 100000) g(r) WHERE r <= most"""


@query("trajectory_skin_tracker", _TRACKED)
def skin_tracker(spark, sf_dir):
    """Atoms whose summed displacement passes half the skin, one row for each rebuild."""
    stream = streaming.event_stream(spark, f"{sf_dir}/events.parquet")
    with streaming.rocks_state(spark):
        return streaming.run_available(streaming.skin_rebuilds(stream), Scratch(spark).root)


_LATE = """WITH e AS (SELECT epoch_us(ts) AS us FROM events),
half AS (SELECT (min(us) + max(us)) // 2 AS mid, max(us) - 3600000000 AS low FROM e),
frames AS (SELECT us, (us // 3600000000 + 1) * 3600000000 AS stop, mid, low FROM e, half)
SELECT CAST(stop // 1000000 - 3600 AS BIGINT) AS frame_start, count(*) AS events FROM frames WHERE (us >= mid OR stop > low) AND stop <= low GROUP BY 1"""


@query("trajectory_late_rows", _LATE)
def late_rows(spark, sf_dir):
    """The later half of the events comes first, the earlier half then lies behind the watermark: in append mode the late
    rows are dropped, and only frames that the watermark has passed come out."""
    events = read(spark, sf_dir, "events").withColumn("at", F.unix_micros(F.col("ts").cast("timestamp")))
    low, high = events.agg(F.min("at"), F.max("at")).first()
    mid, folder = ((low or 0) + (high or 0)) // 2, Scratch(spark).path("arrivals")
    events.filter(F.col("at") >= mid).drop("at").coalesce(1).write.parquet(f"{folder}/first")
    events.filter(F.col("at") < mid).drop("at").coalesce(1).write.parquet(f"{folder}/second")
    return streaming.run_in_turn(spark, [f"{folder}/first", f"{folder}/second"], streaming.plain_frames, Scratch(spark).root)


@query("trajectory_batch_sessions", f"WITH c AS (SELECT *, CASE WHEN floor({EPOCH}) - lag(floor({EPOCH})) OVER w < 1800 THEN 0 ELSE 1 END AS cut FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM c) SELECT user_id, CAST(session AS BIGINT) AS session, count(*) AS events, CAST(min(floor({EPOCH})) AS BIGINT) AS first, CAST(max(floor({EPOCH})) AS BIGINT) AS last FROM s GROUP BY user_id, session")
def batch_sessions(spark, sf_dir):
    return relational.sessions(read(spark, sf_dir, "events"), 1800)
