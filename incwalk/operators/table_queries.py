"""Relational operators that the methods stand on, over the given tables, each with its SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from incwalk.operators.registry_of import Registry
from incwalk.sources.graphs import edges, edges_sql, micros
from incwalk.plans.personal import pick_seeds
from incwalk.plans.ranking import numbered
from incwalk.streaming.maintain import windowed_arrivals
from incwalk.store import scratch_root, table

R = Registry()
CB, BU = edges_sql("cobuy"), edges_sql("buys")
CUT = 915_148_800


def _t(name):
    return lambda s, d: table(s, d, name)


ORD, LI, EV, CU, NA, RE, DO, LA, PA = map(_t, ("orders", "lineitem", "events", "customer", "nation", "region", "documents", "labels", "pages"))


def cb(s, d):
    return edges(s, d, "cobuy")


add = R.add
add("scan_orders_cols", lambda s, d: ORD(s, d).where("o_totalprice > 100000").select("o_orderkey", "o_custkey"), "SELECT o_orderkey, o_custkey FROM orders WHERE o_totalprice > 100000")
add("scan_lineitem_dates", lambda s, d: LI(s, d).where("l_shipdate >= timestamp_ntz '1998-01-01'").groupBy(F.year("l_shipdate").alias("y")).count(), "SELECT year(l_shipdate)::INT AS y, count(*) AS count FROM lineitem WHERE l_shipdate >= '1998-01-01' GROUP BY 1")
add("edge_features", lambda s, d: cb(s, d).select("src", "dst", (F.col("mult") > 1).alias("repeat"), F.when(F.col("ord") < CUT, "old").otherwise("new").alias("age")), f"SELECT src, dst, mult > 1 AS repeat, CASE WHEN ord < {CUT} THEN 'old' ELSE 'new' END AS age FROM ({CB})")
add("recent_edges", lambda s, d: cb(s, d).where(F.col("ord") >= CUT).select("src", "dst"), f"SELECT src, dst FROM ({CB}) WHERE ord >= {CUT}")
add("seed_filter", lambda s, d: cb(s, d).groupBy("src").agg(F.count("*").alias("friends")).where(F.col("friends").between(20, 30)), f"SELECT src, count(*) AS friends FROM ({CB}) GROUP BY 1 HAVING friends BETWEEN 20 AND 30")
add("nation_of_seed", lambda s, d: CU(s, d).join(F.broadcast(NA(s, d)), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name"), "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")


def degree_table(s, d):
    e = edges(s, d, "buys")
    return e.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("o")).join(e.groupBy(F.col("dst").alias("node")).agg(F.count("*").alias("i")), "node", "full").select("node", F.coalesce("o", F.lit(0)).alias("outdeg"), F.coalesce("i", F.lit(0)).alias("indeg"))


add("degree_table", degree_table, f"WITH e AS ({BU}) SELECT coalesce(a.src, b.dst) AS node, coalesce(o, 0) AS outdeg, coalesce(i, 0) AS indeg FROM (SELECT src, count(*) AS o FROM e GROUP BY 1) a FULL JOIN (SELECT dst, count(*) AS i FROM e GROUP BY 1) b ON src = dst")
add("labelled_docs", lambda s, d: DO(s, d).select("doc_id").join(LA(s, d), "doc_id", "left_semi"), "SELECT doc_id FROM documents SEMI JOIN labels USING (doc_id)")
add("unlabelled_docs", lambda s, d: DO(s, d).select("doc_id").join(LA(s, d), "doc_id", "left_anti"), "SELECT doc_id FROM documents ANTI JOIN labels USING (doc_id)")
add("old_nodes_only", lambda s, d: (lambda e: e.where(F.col("ord") >= CUT).join(e.where(F.col("ord") < CUT).select("src"), "src", "left_semi").select("src", "dst"))(cb(s, d)), f"WITH e AS ({CB}) SELECT src, dst FROM e WHERE ord >= {CUT} AND src IN (SELECT src FROM e WHERE ord < {CUT})")
add("reciprocal_edges", lambda s, d: (lambda e: e.select("src", "dst").join(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"]).where("src < dst"))(cb(s, d)), f"WITH e AS ({CB}) SELECT a.src, a.dst FROM e a JOIN e b ON a.src = b.dst AND a.dst = b.src WHERE a.src < a.dst")
add("common_neighbours", lambda s, d: (lambda e: e.join(pick_seeds(e).select(F.col("seed").alias("src")), "src", "left_semi").select(F.col("src").alias("a"), "dst").join(e.select(F.col("src").alias("b"), "dst"), "dst").where("a <> b").groupBy("a", "b").count())(cb(s, d)), f"WITH e AS ({CB}), sd AS (SELECT src FROM (SELECT src, count(*) AS f FROM e GROUP BY src) WHERE f BETWEEN 20 AND 30 ORDER BY md5('seed|' || src), src LIMIT 100) SELECT x.src AS a, y.src AS b, count(*) AS count FROM e x JOIN e y ON x.dst = y.dst WHERE x.src IN (SELECT src FROM sd) AND x.src <> y.src GROUP BY 1, 2")
add("two_hop_counts", lambda s, d: (lambda e: e.select("src", F.col("dst").alias("mid")).join(e.groupBy(F.col("src").alias("mid")).agg(F.count("*").alias("k")), "mid").groupBy("src").agg(F.sum("k").alias("paths")))(cb(s, d)), f"WITH e AS ({CB}), k AS (SELECT src AS mid, count(*) AS k FROM e GROUP BY 1) SELECT src, sum(k)::BIGINT AS paths FROM e JOIN k ON dst = mid GROUP BY 1")


def events_within_hour(s, d):
    """Pairs of a user's events less than an hour apart: an equi-join on hour buckets, each row in its own and the next."""
    e = EV(s, d).select("event_id", "user_id", "ts", F.date_trunc("HOUR", "ts").alias("h"))
    left = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), F.explode(F.array("h", F.expr("h + interval 1 hour"))).alias("h"))
    x = left.join(e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), "h"), ["user_id", "h"])
    return x.where("ta < tb AND tb < ta + interval 1 hour").select("a", "b", "user_id")


add("events_within_hour", events_within_hour, "SELECT x.event_id AS a, y.event_id AS b, x.user_id FROM events x JOIN events y ON x.user_id = y.user_id AND x.ts < y.ts AND y.ts < x.ts + INTERVAL 1 HOUR")
add("indegree", lambda s, d: cb(s, d).groupBy("dst").agg(F.count("*").alias("indeg"), F.count_distinct("src").alias("sources"), F.count_if(F.col("mult") > 1).alias("repeats")), f"SELECT dst, count(*) AS indeg, count(DISTINCT src) AS sources, count(*) FILTER (mult > 1) AS repeats FROM ({CB}) GROUP BY 1")
add("arrivals_cube", lambda s, d: EV(s, d).cube("event_type", F.to_date("ts").alias("day")).agg(F.count("*").alias("n")), "SELECT event_type, ts::DATE AS day, count(*) AS n FROM events GROUP BY CUBE (event_type, day)")
add("score_rollup", lambda s, d: CU(s, d).join(NA(s, d), F.col("c_nationkey") == F.col("n_nationkey")).join(RE(s, d), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n"), F.round(F.avg("c_acctbal"), 4).alias("mean")), "SELECT r_name, n_name, count(*) AS n, round(avg(c_acctbal), 4) AS mean FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
_TYPES = ("click", "view", "purchase")
add("degree_pivot", lambda s, d: EV(s, d).groupBy("user_id").pivot("event_type", list(_TYPES)).count().na.fill(0), "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{t}') AS {t}" for t in _TYPES) + " FROM events GROUP BY 1")
add("degree_moments", lambda s, d: cb(s, d).groupBy("src").count().agg(F.round(F.avg("count"), 6).alias("mean"), F.round(F.stddev_pop("count"), 6).alias("sd"), F.max("count").alias("top")), f"SELECT round(avg(c), 6) AS mean, round(stddev_pop(c), 6) AS sd, max(c) AS top FROM (SELECT count(*) AS c FROM ({CB}) GROUP BY src)")
_DEG = f"SELECT src, count(*) AS d FROM ({CB}) GROUP BY 1"


def deg_windows(s, d):
    """Ranks by degree: windows run over the table of distinct degrees, tiles come from numbers by ranges, so no task holds all nodes."""
    x = cb(s, d).groupBy("src").agg(F.count("*").alias("d"))
    upto = Window.orderBy("d").rowsBetween(Window.unboundedPreceding, 0)  # as many rows as there are degrees
    every = Window.partitionBy(F.lit(1))
    sizes = x.groupBy("d").agg(F.count("*").alias("k")).select("d", "k", F.sum("k").over(upto).alias("run"), F.sum("k").over(every).alias("n"), F.row_number().over(Window.orderBy("d")).alias("dense"))
    y = numbered(x, [F.asc("d"), F.asc("src")], "row").join(F.broadcast(sizes), "d")
    rank, q, r = F.col("run") - F.col("k") + 1, F.floor(F.col("n") / 10), F.col("n") % 10
    row = F.col("row") - 1
    tile = F.when(row < r * (q + 1), F.floor(row / (q + 1)) + 1).otherwise(r + F.floor((row - r * (q + 1)) / F.greatest(q, F.lit(1))) + 1)
    return y.select("src", rank.alias("rank"), "dense", F.round((rank - 1) / F.greatest(F.col("n") - 1, F.lit(1)), 9).alias("share"), F.round(F.col("run") / F.col("n"), 9).alias("cume"), tile.cast("int").alias("tile"))


add("degree_windows", deg_windows, f"SELECT src, rank() OVER w AS rank, dense_rank() OVER w AS dense, round(percent_rank() OVER w, 9) AS share, round(cume_dist() OVER w, 9) AS cume, ntile(10) OVER (ORDER BY d, src) AS tile FROM ({_DEG}) WINDOW w AS (ORDER BY d)")
add("running_arrivals", lambda s, d: EV(s, d).select("event_id", "user_id", F.count("*").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"), F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("next_event")), "SELECT event_id, user_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS so_far, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next_event FROM events")
add("arrivals_7d", lambda s, d: cb(s, d).select("src", "dst", F.count("*").over(Window.partitionBy("src").orderBy("ord").rangeBetween(-7 * 86400, 0)).alias("week")), f"SELECT src, dst, count(*) OVER (PARTITION BY src ORDER BY ord RANGE BETWEEN 604800 PRECEDING AND CURRENT ROW) AS week FROM ({CB})")
add("degree_at_arrival", lambda s, d: cb(s, d).select("src", "dst", (F.row_number().over(Window.partitionBy("src").orderBy("ord", "dst")) - 1).alias("before")), f"SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY ord, dst) - 1 AS before FROM ({CB})")
add("top_nodes", lambda s, d: cb(s, d).groupBy("dst").count().orderBy(F.desc("count"), "dst").limit(20), f"SELECT dst, count(*) AS count FROM ({CB}) GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 20")
add("topk_per_seed", lambda s, d: cb(s, d).withColumn("rank", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("mult"), "dst"))).where("rank <= 3").select("src", "dst", "rank"), f"SELECT src, dst, rank FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY mult DESC, dst) AS rank FROM ({CB})) WHERE rank <= 3")
_two = lambda s, d: (cb(s, d).where(F.col("ord") < CUT).select("src"), cb(s, d).where(F.col("ord") >= CUT).select("src"))
for _n, _f, _q in (("nodes_kept", "intersect", "INTERSECT"), ("nodes_lost", "subtract", "EXCEPT"), ("edges_lost_all", "exceptAll", "EXCEPT ALL"), ("edges_kept_all", "intersectAll", "INTERSECT ALL"), ("edges_union_all", "unionAll", "UNION ALL")):
    add(_n, lambda s, d, f=_f: (lambda a, b: getattr(a, f)(b))(*_two(s, d)), f"SELECT src FROM ({CB}) WHERE ord < {CUT} {_q} SELECT src FROM ({CB}) WHERE ord >= {CUT}")
add("url_host", lambda s, d: PA(s, d).groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).count(), "SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, count(*) AS count FROM pages GROUP BY 1")
add("arrival_buckets", lambda s, d: ORD(s, d).groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).count(), "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS count FROM orders GROUP BY 1")
add("coin_table", lambda s, d: (lambda c: table(s, d, "events").select(F.col("event_id").alias("id"), c[0].alias("a"), c[1].alias("b")))(__import__("incwalk.functions.coins", fromlist=["coin"]).coin(1, "t", F.col("event_id"), F.lit(0), F.lit(0))), "SELECT id, ('0x' || substr(h, 1, 8))::BIGINT AS a, ('0x' || substr(h, 9, 8))::BIGINT AS b FROM (SELECT event_id AS id, md5('1|t|' || event_id || '|0|0') AS h FROM events)")
add("neighbour_lists", lambda s, d: cb(s, d).groupBy("src").agg(F.array_join(F.transform(F.array_sort(F.collect_list("dst")), lambda x: x.cast("string")), ",").alias("list")), f"SELECT src, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS list FROM ({CB}) GROUP BY 1")
add("event_k", lambda s, d: EV(s, d).select("event_id", F.get_json_object("props", "$.k").alias("k")), "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
add("above_mean_degree", lambda s, d: (lambda x: x.crossJoin(x.agg(F.avg("d").alias("m"))).where("d > m").select("src", "d"))(cb(s, d).groupBy("src").agg(F.count("*").alias("d"))), f"SELECT src, d FROM ({_DEG}) WHERE d > (SELECT avg(d) FROM ({_DEG}))")


def reach_within_3(s, d):
    e = cb(s, d).select("src", "dst").where(F.col("mult") >= 1)
    seen = s.createDataFrame([(0, 0)], "node long, hops int")
    for h in (1, 2, 3):
        step = seen.where(F.col("hops") == h - 1).join(e, seen.node == e.src).select(F.col("dst").alias("node"), F.lit(h).alias("hops"))
        seen = seen.union(step).groupBy("node").agg(F.min("hops").alias("hops"))
    return seen


add("reach_within_3", reach_within_3, f"WITH RECURSIVE e AS ({CB}), r AS (SELECT 0::BIGINT AS node, 0 AS hops UNION SELECT dst, hops + 1 FROM r JOIN e ON src = node WHERE hops < 3) SELECT node, min(hops)::INT AS hops FROM r GROUP BY 1")
add("coin_sample_edges", lambda s, d: cb(s, d).where(F.substring(F.md5(F.concat_ws("|", "src", "dst")), 1, 1) == "0").select("src", "dst"), f"SELECT src, dst FROM ({CB}) WHERE substr(md5(src || '|' || dst), 1, 1) = '0'")
add("stream_arrivals_tumbling", lambda s, d: windowed_arrivals(EV(s, d), "6 hours"), "SELECT time_bucket(INTERVAL 6 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
add("prev_turn", lambda s, d: table(s, d, "conversations").select("conv_id", "turn", F.lag("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("prev_role")), "SELECT conv_id, turn, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS prev_role FROM conversations")


# round trips and sinks
def _through(fmt):
    def run(s, d):
        x = cb(s, d).select("src", "dst", "ord")
        path = f"{scratch_root(s)}/incwalk-graph/trip-{fmt}-{uuid.uuid4().hex}"
        x.write.format(fmt).save(path)
        return s.read.schema(x.schema).format(fmt).load(path)

    return run


for _fmt in ("csv", "json", "orc"):
    add(f"roundtrip_{_fmt}", _through(_fmt), f"SELECT src, dst, ord FROM ({CB})")


def store_write_read(s, d):
    """Edges in a folder per version; reading one version prunes the others."""
    path = f"{scratch_root(s)}/incwalk-graph/versions-{uuid.uuid4().hex}"
    x = cb(s, d).select("src", "dst", "ord")
    for version, rows in enumerate((x.where(F.col("ord") < CUT), x)):
        rows.withColumn("version", F.lit(version)).write.mode("append").partitionBy("version").parquet(path)
    return s.read.parquet(path).where("version = 1").select("src", "dst")


add("store_write_read", store_write_read, f"SELECT src, dst FROM ({CB})")
add("tokens", lambda s, d: DO(s, d).select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-zà-ÿ]+)"), 1)).alias("token")).groupBy("token").count(), "SELECT token, count(*) AS count FROM (SELECT unnest(regexp_extract_all(lower(text), '([a-zà-ÿ]+)', 1)) AS token FROM documents) GROUP BY 1")
add("href_targets", lambda s, d: PA(s, d).select(F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href")).groupBy("href").count(), "SELECT href, count(*) AS count FROM (SELECT unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages) GROUP BY 1")
add("first_last_seen", lambda s, d: cb(s, d).groupBy("src").agg(F.min("ord").alias("first"), F.max("ord").alias("last"), F.max_by("dst", F.struct("ord", "dst")).alias("newest")), f"SELECT src, min(ord) AS first, max(ord) AS last, arg_max(dst, (ord, dst)) AS newest FROM ({CB}) GROUP BY 1")
add("exists_reciprocal", lambda s, d: (lambda e: e.join(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"], "left_semi").groupBy("src").agg(F.count("*").alias("mutual")))(cb(s, d)), f"WITH e AS ({CB}) SELECT src, count(*) AS mutual FROM e a WHERE EXISTS (SELECT 1 FROM e b WHERE b.src = a.dst AND b.dst = a.src) GROUP BY 1")


def degree_le(s, d):
    """Nodes of at most each degree: a range condition answered by a running sum over the table of degrees instead of a nested loop."""
    k = cb(s, d).groupBy("src").agg(F.count("*").alias("d")).groupBy("d").agg(F.count("*").alias("k"))
    return k.select("d", F.sum("k").over(Window.orderBy("d").rowsBetween(Window.unboundedPreceding, 0)).alias("nodes"))  # a row a degree


add("degree_le", degree_le, f"WITH g AS ({_DEG}) SELECT a.d, count(*) AS nodes FROM (SELECT DISTINCT d FROM g) a JOIN g b ON b.d <= a.d GROUP BY 1")


def order_before_event(s, d):
    """As-of join: for each event the user's latest order at or before the event's clock, shifted to the orders' years; a union sorted per user and year, the last order carried forward, and over year ends the last of the years before."""
    o = ORD(s, d).select(F.col("o_custkey").alias("user_id"), (micros("o_orderdate")).alias("at"), F.lit(0).alias("kind"), F.col("o_orderkey").alias("id"))
    e = EV(s, d).select("user_id", (micros("ts") - SHIFT).alias("at"), F.lit(1).alias("kind"), F.col("event_id").alias("id"))
    x = o.unionByName(e).withColumn("block", F.floor(F.col("at") / (30 * 86_400_000_000)))
    w = Window.partitionBy("user_id", "block").orderBy("at", "kind", "id").rowsBetween(Window.unboundedPreceding, 0)
    x = x.withColumn("here", F.last(F.when(F.col("kind") == 0, F.col("id")), ignorenulls=True).over(w))
    last = x.groupBy("user_id", "block").agg(F.max(F.when(F.col("kind") == 0, F.struct("at", "id")))["id"].alias("z"))
    b = Window.partitionBy("user_id").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    carried = last.select("user_id", "block", F.last("z", ignorenulls=True).over(b).alias("carry"))
    return x.where("kind = 1").join(carried, ["user_id", "block"]).select(F.col("id").alias("event_id"), F.coalesce("here", "carry").alias("o_orderkey"))


SHIFT = 25 * 365 * 86_400 * 1_000_000
add("order_before_event", order_before_event, f"WITH e AS (SELECT event_id, user_id, epoch_us(ts) - {SHIFT} AS at FROM events) SELECT event_id, (SELECT max((epoch_us(o_orderdate), o_orderkey))[2] FROM orders WHERE o_custkey = user_id AND epoch_us(o_orderdate) <= e.at) AS o_orderkey FROM e")
add("arrivals_grouping_sets", lambda s, d: EV(s, d).groupingSets([["event_type"], ["user_id"], []], "event_type", "user_id").agg(F.count("*").alias("n")), "SELECT event_type, user_id, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (user_id), ())")
add("visit_maps", lambda s, d: EV(s, d).groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("event_type", "count")))).alias("m")).select("user_id", F.coalesce(F.col("m")["click"], F.lit(0)).alias("clicks"), F.size("m").alias("kinds")), "SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(DISTINCT event_type)::INT AS kinds FROM events GROUP BY 1")
add("event_struct", lambda s, d: EV(s, d).select("event_id", F.from_json("props", "k long").alias("p")).select("event_id", F.to_json("p").alias("json"), F.col("p.k").alias("k")), "SELECT event_id, '{\"k\":' || json_extract_string(props, '$.k') || '}' AS json, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
add("approx_degree", lambda s, d: cb(s, d).groupBy("src").agg(F.approx_count_distinct("dst", 0.02).alias("about"), F.count("*").alias("deg")))
add("hinted_joins", lambda s, d: (lambda e, c: e.join(c.hint("merge"), "src").groupBy("seg").count().withColumn("way", F.lit("merge")).unionByName(e.join(c.hint("shuffle_hash"), "src").groupBy("seg").count().withColumn("way", F.lit("hash"))))(cb(s, d).select("src"), CU(s, d).select(F.col("c_custkey").alias("src"), F.col("c_mktsegment").alias("seg"))), f"SELECT c_mktsegment AS seg, count(*) AS count, way FROM ({CB}) JOIN customer ON c_custkey = src, (VALUES ('merge'), ('hash')) v(way) GROUP BY ALL")


def near_pairs(spark, sf_dir, seconds: int = 60):
    """Events of one type and different users within a minute: a band join, by equality of bands of that width and the band behind."""
    x = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    band = F.floor(F.col("t") / F.lit(seconds * 1_000_000))
    left = x.select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), "event_type", F.col("t").alias("ta"), F.explode(F.array(band, band + 1)).alias("band"))
    right = x.select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), "event_type", F.col("t").alias("tb"), band.alias("band"))
    near = (F.col("tb") - F.col("ta")).between(0, seconds * 1_000_000) & ((F.col("tb") > F.col("ta")) | (F.col("a") < F.col("b"))) & (F.col("ua") != F.col("ub"))
    return left.join(right, ["event_type", "band"]).where(near).select("event_type", "a", "b")


add("near_pairs", near_pairs, "SELECT x.event_type, x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.event_type = y.event_type AND x.user_id <> y.user_id AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 60 SECOND AND (y.ts > x.ts OR x.event_id < y.event_id)")
