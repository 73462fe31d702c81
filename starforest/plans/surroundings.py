"""Queries of the operators around the methods: relational forms, windows, scalar functions, sources, consumers, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from starforest import baselines, consumers, sources, sqlapi, streaming
from starforest.algebra.kernel import sampled_product
from starforest.components.connectivity import any_spanning_forest, connected_components
from starforest.forest import steps
from starforest.forest.loop import minimum_spanning_forest
from starforest.forest.measures import min_outgoing_per_tree
from starforest.forest.shortcut import shortcut_step
from starforest.graph import builders, generators
from starforest.graph.order import canonical_edges, mixed, rank_edges, vertices_of, with_random_weights
from starforest.plans import catalogue as cat
from starforest.plans import oracle, parents
from starforest.plans.catalogue import add, grow, ranked
from starforest.runtime import read_table, shared_dir


def _scratch(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"


# ---- filters, joins, aggregates -------------------------------------------------------------------------------------
add("filter_range_lines", lambda s, d: read_table(s, d, "lineitem").where(F.col("l_returnflag").isin("R", "A") & F.col("l_quantity").between(10, 20) & F.col("l_linestatus").rlike("^[OF]$") & ~F.col("l_tax").eqNullSafe(0.0)).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem WHERE l_returnflag IN ('R', 'A') AND l_quantity BETWEEN 10 AND 20 AND regexp_matches(l_linestatus, '^[OF]$') AND l_tax IS DISTINCT FROM 0.0 GROUP BY 1, 2")


def _region_pairs(s: SparkSession, d: str) -> DataFrame:
    n = read_table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("a"), "n_regionkey")
    return n.join(n.withColumnRenamed("a", "b"), "n_regionkey").where("a < b").select("a", "b")


add("theta_pairs_nation", _region_pairs, "SELECT CAST(x.n_nationkey AS BIGINT) AS a, CAST(y.n_nationkey AS BIGINT) AS b FROM nation x JOIN nation y ON x.n_regionkey = y.n_regionkey AND x.n_nationkey < y.n_nationkey")


def _lateral(s: SparkSession, d: str) -> DataFrame:
    e = cat._entries(s, d, "nation")
    e.createOrReplaceTempView("_nation_entries")
    vertices_of(ranked(s, d, "nation")).createOrReplaceTempView("_nation_vertices")
    return s.sql("SELECT x.v, y.j, y.w FROM _nation_vertices x, LATERAL (SELECT j, w FROM _nation_entries e WHERE e.i = x.v ORDER BY rank LIMIT 2) y")


_NATION = oracle.RANKED.format(oracle.EDGES["nation"])
_NATION_ENTRIES = f"{_NATION}, a AS (SELECT lo AS i, hi AS j, rank, w FROM e UNION ALL SELECT hi, lo, rank, w FROM e)"
add("lateral_two_lightest_nation", _lateral, f"WITH {_NATION_ENTRIES} SELECT i AS v, j, w FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY rank) AS k FROM a) WHERE k <= 2")
add("agg_hash_vs_sort_lightest", lambda s, d: cat._entries(s, d).groupBy(F.col("i").alias("v")).agg(F.min("rank").alias("rank"), F.min(F.struct("rank", "j")).alias("m")).select("v", "rank", (F.col("rank") == F.col("m.rank")).alias("same")), f"WITH {cat._SYM} SELECT i AS v, min(rank) AS rank, true AS same FROM a GROUP BY i")
add("distinct_components_returns", lambda s, d: connected_components(builders.returns(s, d)).agg(F.countDistinct("component").alias("components"), F.count("*").alias("n")), f"SELECT count(DISTINCT component) AS components, count(*) AS n FROM ({oracle.components(oracle.EDGES['returns'])})")
add("weight_quantiles_trade", lambda s, d: builders.trade(s, d).select(F.expr("percentile(w, array(0.25D, 0.5D, 0.75D))").alias("q")).select(F.posexplode("q").alias("k", "w")).select(F.col("k").cast("long").alias("k"), F.floor("w").alias("w")), " UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS k, CAST(floor(quantile_cont(w, {q})) AS BIGINT) AS w FROM ({oracle.EDGES['trade']})" for k, q in enumerate((0.25, 0.5, 0.75))))
add("forest_grouping_sets", lambda s, d: cat._placed(s, d).groupingSets([["n_regionkey"], ["c_mktsegment"], []], "n_regionkey", "c_mktsegment").agg(F.sum("w").alias("w"), F.count("*").alias("n")), f"{cat._PLACED} SELECT n_regionkey, c_mktsegment, CAST(sum(w) AS BIGINT) AS w, count(*) AS n FROM p GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment), ())")
_SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")


def _segments(s: SparkSession, d: str) -> DataFrame:
    return cat._placed(s, d).groupBy("n_regionkey").pivot("c_mktsegment", list(_SEGMENTS)).agg(F.sum("w"))


add("pivot_forest_segments", _segments, f"{cat._PLACED} SELECT n_regionkey, {', '.join(f'''CAST(sum(w) FILTER (c_mktsegment = '{x}') AS BIGINT) AS "{x}"''' for x in _SEGMENTS)} FROM p GROUP BY n_regionkey")
add("unpivot_forest_segments", lambda s, d: _segments(s, d).unpivot("n_regionkey", list(_SEGMENTS), "segment", "w"), f"{cat._PLACED} SELECT n_regionkey, c_mktsegment AS segment, CAST(sum(w) AS BIGINT) AS w FROM p GROUP BY 1, 2")


def _set_operations(s: SparkSession, d: str) -> DataFrame:
    a, b = (grow(s, d, "nation", shortcut=v).forest.select("lo", "hi") for v in ("queried", "prefetched"))
    every = (("union", a.union(b).distinct()), ("intersect", a.intersectAll(b)), ("except", a.exceptAll(b)))
    one, two, three = (df.agg(F.lit(name).alias("what"), F.count("*").alias("n")) for name, df in every)
    return one.union(two).union(three)


add("forest_union_intersect_except", _set_operations, f"WITH {oracle.forest_ctes(oracle.EDGES['nation'])} SELECT what, CASE what WHEN 'except' THEN 0 ELSE (SELECT count(*) FROM f) END AS n FROM (VALUES ('union'), ('intersect'), ('except')) t(what)")

# ---- windows --------------------------------------------------------------------------------------------------------
def _by_user():
    return Window.partitionBy("user_id").orderBy("us", "event_id")


_EV = "(SELECT *, epoch_us(ts) AS us FROM events)"
add("event_gaps_lead_lag", lambda s, d: cat._micros(s, d).select("event_id", (F.col("us") - F.lag("us").over(_by_user())).alias("before"), (F.lead("us").over(_by_user()) - F.col("us")).alias("after"), F.first("event_id").over(_by_user()).alias("first")), f"SELECT event_id, us - lag(us) OVER w AS before, lead(us) OVER w - us AS after, first_value(event_id) OVER w AS first FROM {_EV} WINDOW w AS (PARTITION BY user_id ORDER BY us, event_id)")
add("weight_curve_trade", lambda s, d: cat._placed(s, d).select("c_nationkey", "w", F.sum("w").over(Window.partitionBy("c_nationkey").orderBy("w").rangeBetween(Window.unboundedPreceding, 0)).alias("total")), f"{cat._PLACED} SELECT c_nationkey, w, CAST(sum(w) OVER (PARTITION BY c_nationkey ORDER BY w RANGE UNBOUNDED PRECEDING) AS BIGINT) AS total FROM p")
add("events_per_interval", lambda s, d: cat._micros(s, d).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("n")), f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY us RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM {_EV}")


def _top_two(s: SparkSession, d: str) -> DataFrame:
    found = grow(s, d, "turns")
    placed = found.forest.join(found.components().withColumnRenamed("v", "lo"), "lo")
    return placed.withColumn("k", F.row_number().over(Window.partitionBy("component").orderBy(F.desc("rank")))).where("k <= 2").select("component", "lo", "hi", "w")


add("topk_per_component_turns", _top_two, f"SELECT component, lo, hi, w FROM (SELECT *, min(lo) OVER (PARTITION BY lo // 16000) AS component, row_number() OVER (PARTITION BY lo // 16000 ORDER BY w DESC, lo DESC, hi DESC) AS k FROM ({oracle.EDGES['turns']})) WHERE k <= 2")

# ---- scalar functions -----------------------------------------------------------------------------------------------
add("scalar_string_links", lambda s, d: read_table(s, d, "pages").select("page_id", F.length("url").cast("long").alias("n"), F.lower(F.trim("url")).alias("u"), F.sha2("url", 256).alias("h"), F.concat_ws("-", F.substring("url", 1, 4), F.lit("x")).alias("c")), "SELECT page_id, length(url) AS n, lower(trim(url)) AS u, sha256(url) AS h, concat_ws('-', substr(url, 1, 4), 'x') AS c FROM pages")
add("scalar_date_gaps", lambda s, d: read_table(s, d, "events").groupBy(F.dayofmonth("ts").cast("long").alias("day"), F.hour("ts").cast("long").alias("hour")).agg(F.count("*").alias("n")), "SELECT day(ts) AS day, hour(ts) AS hour, count(*) AS n FROM events GROUP BY 1, 2")
add("scalar_math_mixer", lambda s, d: read_table(s, d, "events").select("event_id", mixed(7, F.col("event_id")).alias("m"), F.shiftleft("event_id", 2).alias("s"), F.col("event_id").bitwiseXOR(F.lit(5).cast("long")).alias("x"), F.floor(F.sqrt("event_id")).alias("r")), f"SELECT event_id, {oracle.mixed_sql('7', 'event_id')} AS m, event_id * 4 AS s, xor(event_id, CAST(5 AS BIGINT)) AS x, CAST(floor(sqrt(event_id)) AS BIGINT) AS r FROM events")


def _region_map(s: SparkSession, d: str) -> DataFrame:
    # One map of 25 nations, a table whose size does not grow with the data.
    m = read_table(s, d, "nation").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_regionkey"))).alias("m"))
    return read_table(s, d, "customer").select("c_nationkey").join(F.broadcast(m)).groupBy(F.element_at("m", F.col("c_nationkey")).cast("long").alias("region")).agg(F.count("*").alias("n"))


add("scalar_map_regions", _region_map, "SELECT CAST(n_regionkey AS BIGINT) AS region, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
add("scalar_conditional", lambda s, d: read_table(s, d, "events").select("event_id", F.when(F.col("event_type") == "click", 1).when(F.col("event_type") == "view", 2).otherwise(3).cast("long").alias("c"), F.coalesce(F.nullif("event_type", F.lit("error")), F.lit("-")).alias("t"), F.greatest("event_id", "user_id").alias("g"), F.least("event_id", "user_id").alias("l")), "SELECT event_id, CAST(CASE event_type WHEN 'click' THEN 1 WHEN 'view' THEN 2 ELSE 3 END AS BIGINT) AS c, coalesce(nullif(event_type, 'error'), '-') AS t, greatest(event_id, user_id) AS g, least(event_id, user_id) AS l FROM events")

# ---- sources and sinks ----------------------------------------------------------------------------------------------
def _bucketed(s: SparkSession, d: str) -> DataFrame:
    name = f"starforest_edges_{uuid.uuid4().hex}"
    sources.write_edges(builders.trade(s, d), name, path=_scratch(s, "bucketed"))
    return s.table(name)


def _lines(s: SparkSession, d: str, line: str, graph: str) -> str:
    path = _scratch(s, "lines")
    builders.GRAPHS[graph](s, d).select(F.expr(line).alias("value")).write.text(path)
    return path


def _matrix(s: SparkSession, d: str) -> DataFrame:
    path = _scratch(s, "matrix")
    head = s.createDataFrame([(0, "%%MatrixMarket matrix coordinate integer symmetric"), (1, "400 400 300")], "k long, value string")
    body = builders.nation(s, d).select(F.lit(2).cast("long"), F.expr("concat_ws(' ', lo, hi, w)"))
    head.union(body).coalesce(1).sortWithinPartitions("k").select("value").write.text(path)
    return sources.read_matrix_market(s, path)


def _json(s: SparkSession, d: str) -> DataFrame:
    path = _scratch(s, "json")
    builders.turns(s, d).select(F.col("lo").alias("a"), F.col("hi").alias("b"), "w").write.json(path)
    return sources.read_json_edges(s, path)


def _uniform_source(s: SparkSession, d: str) -> DataFrame:
    sources.register_sources(s)
    # The source's rows of the customers' keys: as many are made as the largest key asks for.
    ids = cat.keys(s, d, "customer", "c_custkey")
    rows = s.read.format("uniform_graph").options(n=1000, m=(ids.agg(F.max("id")).first()[0] or 0) + 1, seed=1).load()
    return canonical_edges(rows.join(ids, "id"))


def _named_places(s: SparkSession, d: str) -> DataFrame:
    n = read_table(s, d, "nation").join(read_table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    e, names = sources.relabel_dense(s, n.select(F.col("n_name").alias("a"), F.col("r_name").alias("b"), F.col("n_nationkey").cast("long").alias("w")))
    x, y = (names.select(F.col("v").alias(c), F.col("name").alias(f"{c}_name")) for c in ("lo", "hi"))
    return e.join(x, "lo").join(y, "hi").select("lo_name", "hi_name", "w")


add("roundtrip_bucketed_edges", _bucketed, oracle.EDGES["trade"])
add("edge_list_parsed", lambda s, d: sources.read_edge_list(s, _lines(s, d, "concat_ws('\t', lo, hi, w)", "supply")), oracle.EDGES["supply"])
add("road_text_parsed", lambda s, d: sources.read_road_text(s, _lines(s, d, "concat_ws(' ', 'a', lo, hi, w)", "lattice")), oracle.EDGES["lattice"])
add("matrix_market_parsed", _matrix, oracle.EDGES["nation"])
add("json_edges_parsed", _json, oracle.EDGES["turns"])
add("source_uniform", _uniform_source, cat._uniform_sql(1000, 0, ids="(SELECT CAST(c_custkey AS BIGINT) AS id FROM customer)"))
add("relabelled_places", _named_places, "SELECT least(n_name, r_name) AS lo_name, greatest(n_name, r_name) AS hi_name, CAST(n_nationkey AS BIGINT) AS w FROM nation JOIN region ON n_regionkey = r_regionkey")
add("edges_vectors_radius", lambda s, d: builders.vectors(s, d), oracle.VECTOR_EDGES)
add("forest_vectors_radius", lambda s, d: minimum_spanning_forest(rank_edges(builders.vectors(s, d))).forest.select("lo", "hi", "w"), oracle.forest(oracle.VECTOR_EDGES))


def _crossing(s: SparkSession, d: str) -> DataFrame:
    e = rank_edges(builders.vectors(s, d), dense=True)
    label = read_table(s, d, "embeddings").select(builders.vertex("vec_id", "vec").alias("v"), F.col("label").cast("long").alias("p"))
    return min_outgoing_per_tree(e, label).withColumnRenamed("root", "label")


add("lightest_crossing_edge_per_label", _crossing, f"WITH {oracle.RANKED.format(oracle.VECTOR_EDGES)}, l AS (SELECT vec_id * 16 + 8 AS v, CAST(label AS BIGINT) AS p FROM embeddings), c AS (SELECT rank, x.p AS a, y.p AS b FROM e JOIN l x ON lo = x.v JOIN l y ON hi = y.v WHERE x.p <> y.p) SELECT label, min(rank) AS rank FROM (SELECT a AS label, rank FROM c UNION ALL SELECT b, rank FROM c) GROUP BY label")


def _products(s: SparkSession, d: str) -> DataFrame:
    e = cat._entries(s, d, "turns").withColumn("a", F.col("w").cast("double"))
    rows = e.select(F.col("i").alias("v")).distinct()
    x, y = (rows.select("v", F.expr(f"array(double(v % {a}), double(v % {b}))").alias(n)) for n, a, b in (("x", 7, 11), ("y", 5, 13)))
    return sampled_product(e, x, y).select("i", "j", F.col("value").cast("long").alias("value"))


add("sampled_product_turns", _products, f"SELECT i, j, CAST(w * ((i % 7) * (j % 5) + (i % 11) * (j % 13)) AS BIGINT) AS value FROM (SELECT lo AS i, hi AS j, w FROM ({oracle.EDGES['turns']}) UNION ALL SELECT hi, lo, w FROM ({oracle.EDGES['turns']}))")

# ---- components, consumers, SQL -------------------------------------------------------------------------------------
add("any_forest_components_returns", lambda s, d: minimum_spanning_forest(rank_edges(any_spanning_forest(builders.returns(s, d)).withColumn("w", F.lit(1).cast("long")))).components(), oracle.components(oracle.EDGES["returns"]))
add("any_forest_size_returns", lambda s, d: any_spanning_forest(builders.returns(s, d)).agg(F.count("*").alias("n")), f"SELECT count(*) - count(DISTINCT component) AS n FROM ({oracle.components(oracle.EDGES['returns'])})")
add("recursive_reach_geo", lambda s, d: sqlapi.reachable(s, builders.geo(s, d), 5, hops=2), f"WITH e AS ({oracle.EDGES['geo']}), a AS (SELECT lo AS i, hi AS j FROM e UNION ALL SELECT hi, lo FROM e) SELECT CAST(5 AS BIGINT) AS v UNION SELECT j FROM a WHERE i = 5 UNION SELECT y.j FROM a x JOIN a y ON x.j = y.i WHERE x.i = 5")


def _depths(s: SparkSession, d: str) -> DataFrame:
    found = grow(s, d, "turns")
    return consumers.root_forest(found.forest, found.components().select(F.col("component").alias("v")).distinct()).select("v", "parent", F.col("depth").cast("long").alias("depth"))


_TURN = oracle.vid("conv_id * 1000 + turn", 12)
add("rooted_depths_turns", _depths, f"SELECT v, parent, depth FROM (SELECT {_TURN} AS v, lag({_TURN}) OVER w AS parent, row_number() OVER w - 1 AS depth, count(*) OVER (PARTITION BY conv_id) AS n FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE n > 1")


def _inserted(s: SparkSession, d: str) -> DataFrame:
    e = rank_edges(builders.nation(s, d), dense=True)
    forest = minimum_spanning_forest(e).forest
    return consumers.insert_edge(forest, e.orderBy(F.desc("rank")).limit(1))


add("insert_edge_nation", _inserted, f"WITH {_NATION} SELECT max(rank) AS rank FROM e")
for _g in ("links", "turns"):
    add(f"forest_{_g}_tied_weights", lambda s, d, g=_g: minimum_spanning_forest(rank_edges(with_random_weights(builders.GRAPHS[g](s, d), 7))).forest.select("lo", "hi", "w"), oracle.forest(f"SELECT lo, hi, {oracle.mixed_sql('7', 'lo', 'hi')} % 255 + 1 AS w FROM ({oracle.EDGES[_g]})"))
add("height_potential_chain", lambda s, d: s.createDataFrame([(steps.height_potential(parents.chain(s, d)),)], "height_sum long"), f"SELECT CAST(sum(h) AS BIGINT) AS height_sum FROM (SELECT root, max(depth) AS h FROM ({parents.CHAIN_ROOTS}) GROUP BY root)")
add("height_potential_chain_stepped", lambda s, d: s.createDataFrame([(steps.height_potential(shortcut_step(parents.chain(s, d))),)], "height_sum long"), f"SELECT CAST(sum((h + 1) // 2) AS BIGINT) AS height_sum FROM (SELECT root, max(depth) AS h FROM ({parents.CHAIN_ROOTS}) GROUP BY root)")
add("forest_complete_graph", lambda s, d: minimum_spanning_forest(rank_edges(generators.complete_graph(s, 40))).forest.select("lo", "hi", "w"), oracle.forest(f"SELECT a AS lo, b AS hi, {oracle.mixed_sql('1', 'a', 'b')} % 1000000 + 1 AS w FROM range(40) x(a), range(40) y(b) WHERE a < b"))
add("kruskal_partitioned_lattice", lambda s, d: (lambda e: e.join(baselines.divide_and_merge_forest(e, parts=16, fan_in=4).select("rank"), "rank").select("lo", "hi", "w"))(ranked(s, d, "lattice")), oracle.forest(oracle.EDGES["lattice"]))

# ---- streams --------------------------------------------------------------------------------------------------------
def _hours(events: DataFrame) -> DataFrame:
    """Edges of an event: its user and its hour of the day, weighing the value in cents; ``slice`` is the day."""
    return events.select((F.dayofyear("ts") - 1).cast("long").alias("slice"), builders.vertex(F.hour("ts"), "event").alias("x"), builders.vertex("user_id", "user").alias("y"), F.round(F.col("value") * 100).cast("long").alias("w")).select("slice", F.least("x", "y").alias("lo"), F.greatest("x", "y").alias("hi"), "w")


_HOURS = f"SELECT CAST(dayofyear(ts) - 1 AS BIGINT) AS slice, least({oracle.vid('hour(ts)', 6)}, {oracle.vid('user_id', 11)}) AS lo, greatest({oracle.vid('hour(ts)', 6)}, {oracle.vid('user_id', 11)}) AS hi, CAST(round(value * 100) AS BIGINT) AS w FROM events"
_WINDOWS = f"SELECT lo * 64 + win AS lo, hi * 64 + win AS hi, min(w) AS w FROM (SELECT *, unnest(range(slice, slice + 3)) AS win FROM ({_HOURS})) GROUP BY 1, 2"
add("stream_sliding_forest", lambda s, d: streaming.sliding_forest(streaming.replay(_hours(streaming.event_stream(s, d))), 3), f"SELECT lo % 64 AS win, lo // 64 AS lo, hi // 64 AS hi, w FROM ({oracle.forest(_WINDOWS)})")
_HOUR_EDGES = f"SELECT lo, hi, min(w) AS w FROM ({_HOURS}) GROUP BY 1, 2"
add("stream_hour_forest", lambda s, d: streaming.stream_forest(_hours(streaming.event_stream(s, d))), oracle.forest(_HOUR_EDGES))
add("stream_running_components", lambda s, d: s.createDataFrame([(streaming.running_components(_hours(streaming.event_stream(s, d)), vertices_of(_hours(read_table(s, d, "events"))).count()),)], "components long"), f"SELECT count(DISTINCT component) AS components FROM ({oracle.components(_HOUR_EDGES)})")
add("stream_static_join", lambda s, d: streaming.replay(streaming.event_stream(s, d).join(F.broadcast(read_table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("k"), "n_name")), F.expr("user_id % 25 = k")).select("event_id", "n_name")), "SELECT event_id, n_name FROM events JOIN nation ON user_id % 25 = n_nationkey")
add("stream_dedup", lambda s, d: streaming.replay(streaming.daily_distinct(streaming.event_stream(s, d))), "SELECT DISTINCT user_id, event_type, CAST(ts AS DATE) AS day FROM events")
add("stream_interval_join", lambda s, d: streaming.replay(streaming.follow_ups(streaming.event_stream(s, d), streaming.event_stream(s, d))), f"SELECT a.user_id, a.event_id AS click, b.event_id AS buy FROM {_EV} a JOIN {_EV} b ON a.user_id = b.user_id AND b.us >= a.us AND b.us < a.us + 3600000000 WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
add("stream_sliding_window_counts", lambda s, d: streaming.replay(streaming.event_stream(s, d).groupBy(F.window("at", "6 hours", "3 hours").alias("win"), "event_type").agg(F.count("*").alias("n")).select(F.unix_micros("win.start").alias("start"), "event_type", "n"), mode="complete"), "SELECT (epoch_us(ts) // 10800000000 - k) * 10800000000 AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) t(k) GROUP BY 1, 2")
