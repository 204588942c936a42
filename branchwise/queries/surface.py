"""The relational surface: degrees, label statistics, set operations, windows, text and JSON columns, renderings of embeddings."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from branchwise.operators import joins
from branchwise.operators.graph import LabeledGraph
from branchwise.plans.pattern import PatternGraph
from branchwise.plans.sqlgen import to_sql
from branchwise.sources import graphs as src
from branchwise.streaming import deltas

from .patterns import A, B, C, cycle
from .registry import graph, on, query, with_views

ABC = cycle(A, B, C)


def count_all():
    return F.count(F.lit(1))


query("o_edges_closed", on("gs", "SELECT src, dst FROM e"))(lambda s, d: graph("gs", s, d).edges.select("src", "dst"))
query("o_degree", on("gd", "SELECT src AS vid, count(*) AS deg FROM e GROUP BY src"))(lambda s, d: graph("gd", s, d).degrees())
query("o_degree_hist", on("gd", "SELECT deg, count(*) AS vertices FROM (SELECT count(*) AS deg FROM e GROUP BY src) GROUP BY deg"))(lambda s, d: graph("gd", s, d).degrees().groupBy("deg").agg(count_all().alias("vertices")))

#: name -> grouping in SQL, grouping in Spark.
GROUPINGS = {
    "o_label_rollup": ("ROLLUP (src_label, dst_label)", lambda e: e.rollup("src_label", "dst_label")),
    "o_label_cube": ("CUBE (src_label, dst_label)", lambda e: e.cube("src_label", "dst_label")),
    "o_label_grouping_sets": ("GROUPING SETS ((src_label), (dst_label))", lambda e: e.groupingSets([[F.col("src_label")], [F.col("dst_label")]], "src_label", "dst_label")),
    "o_label_pairs": ("src_label, dst_label", lambda e: e.groupBy("src_label", "dst_label")),
}
for _name, (_by, _f) in GROUPINGS.items():
    query(_name, on("gd", f"SELECT sl AS src_label, dl AS dst_label, count(*) AS n FROM le GROUP BY {_by.replace('src_label', 'sl').replace('dst_label', 'dl')}"))(lambda s, d, f=_f: f(graph("gd", s, d).edges).agg(count_all().alias("n")).select("src_label", "dst_label", "n"))

query("o_adjacency_lists", on("gs", "SELECT src AS vid, string_agg(CAST(dst AS VARCHAR), ',' ORDER BY dst) AS nbrs FROM e GROUP BY src"))(lambda s, d: graph("gs", s, d).adjacency().select("vid", F.array_join("nbrs", ",").alias("nbrs")))


def _beside(spark, sf_dir, how: str):
    g = graph("gd", spark, sf_dir)
    return g.vertices.join(g.edges.filter(F.col("dst_label") == B).select(F.col("src").alias("vid")), "vid", how).select("vid")


query("o_semi_has_neighbor", on("gd", f"SELECT vid FROM v WHERE vid IN (SELECT src FROM le WHERE dl = '{B}')"))(lambda s, d: _beside(s, d, "left_semi"))
query("o_anti_no_neighbor", on("gd", f"SELECT vid FROM v WHERE vid NOT IN (SELECT src FROM le WHERE dl = '{B}')"))(lambda s, d: _beside(s, d, "left_anti"))


@query("o_common_neighbors", on("gs", "SELECT x.src AS a, y.src AS b, count(*) AS common FROM e x JOIN e y ON x.dst = y.dst WHERE x.src < y.src GROUP BY ALL"))
def o_common_neighbors(spark, sf_dir):
    """Per pair that has any: pairs meet on the neighbour, one side dealt over salts so that a hub is several tasks."""
    salts = 4
    e = graph("gs", spark, sf_dir).edges.select("src", "dst")
    a = e.select(F.col("src").alias("a"), "dst", F.pmod(F.xxhash64("src"), F.lit(salts)).cast("int").alias("salt"))
    b = e.select(F.col("src").alias("b"), "dst", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    return a.join(b, ["dst", "salt"]).filter("a < b").groupBy("a", "b").agg(count_all().alias("common"))


query("o_time_proximity", on("gu", "SELECT a, b FROM pairs"))(lambda s, d: src.user_pairs(src.table(s, d, "events")))
query("o_cross_domains", on("gs", to_sql(PatternGraph((A, B), ()))))(lambda s, d: joins.join_match(graph("gs", s, d), PatternGraph((A, B), ())))


@query("o_top_degree_per_label", with_views("gd", "d AS MATERIALIZED (SELECT src AS vid, sl AS label, count(*) AS deg FROM le GROUP BY ALL)", "SELECT label, vid, deg FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY deg DESC, vid) AS r FROM d) WHERE r <= 3"))
def o_top_degree_per_label(spark, sf_dir):
    g = graph("gd", spark, sf_dir)
    ranked = F.row_number().over(Window.partitionBy("label").orderBy(F.desc("deg"), "vid"))
    return g.degrees().join(g.vertices, "vid").withColumn("r", ranked).filter("r <= 3").select("label", "vid", "deg")


query("o_rank_labels", "SELECT p_brand, n, dense_rank() OVER (ORDER BY n DESC) AS r FROM (SELECT p_brand, count(*) AS n FROM part GROUP BY p_brand)")(
    lambda s, d: src.table(s, d, "part").groupBy("p_brand").agg(count_all().alias("n")).withColumn("r", F.dense_rank().over(Window.orderBy(F.desc("n"))))
)
query("o_lag_turn", "SELECT conv_id, turn, role, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS before FROM conversations")(
    lambda s, d: src.table(s, d, "conversations").select("conv_id", "turn", "role", F.lag("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("before"))
)
query("o_rolling_events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS n FROM events")(
    lambda s, d: src.table(s, d, "events").select("event_id", count_all().over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)).alias("n"))
)

# Edges of a sparse graph beside those of a dense one.
_SPARSE = """li2 AS MATERIALIZED (SELECT DISTINCT l_orderkey AS k0, l_returnflag AS k1, l_linestatus AS k2, l_quantity <= 25 AS k3, l_partkey AS p FROM lineitem),
pairs2 AS MATERIALIZED (SELECT DISTINCT x.p AS a, y.p AS b FROM li2 x JOIN li2 y USING (k0, k1, k2, k3) WHERE x.p < y.p), e2 AS MATERIALIZED (SELECT a AS src, b AS dst FROM pairs2 UNION ALL SELECT b, a FROM pairs2)"""
for _op, _f in {"UNION": lambda a, b: a.union(b).distinct(), "INTERSECT": lambda a, b: a.intersect(b), "EXCEPT": lambda a, b: a.exceptAll(b)}.items():
    query(f"o_edges_{_op.lower()}", with_views("gd", _SPARSE, f"SELECT src, dst FROM e {_op} SELECT src, dst FROM e2"))(lambda s, d, f=_f: f(graph("gd", s, d).edges.select("src", "dst"), graph("gs", s, d).edges.select("src", "dst")))

_HREF = 'href="([^"]+)"'
query("o_href_tokens", f"SELECT DISTINCT page_id, unnest(regexp_extract_all(html, '{_HREF}', 1)) AS href FROM pages")(lambda s, d: src.table(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(_HREF), 1)).alias("href")).distinct())
query("o_host_lang", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/]+/([^/]+)', 1) AS lang FROM pages")(
    lambda s, d: src.table(s, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.regexp_extract("url", "^[a-z]+://[^/]+/([^/]+)", 1).alias("lang"))
)
query("o_json_prop", "SELECT event_id, key, json_extract_string(props, '$.\"' || key || '\"') AS value FROM (SELECT event_id, props, unnest(json_keys(props)) AS key FROM events)")(
    lambda s, d: src.table(s, d, "events").select("event_id", F.explode(F.from_json("props", "map<string,string>")).alias("key", "value"))
)

# Renderings of embeddings, and aggregates over them.
query("o_embedding_arrays", on("gd", f"SELECT array_to_string([m1, m2, m3], ',') AS asg FROM ({to_sql(ABC)})"))(lambda s, d: joins.as_array(joins.join_match(graph("gd", s, d), ABC)).select(F.array_join("asg", ",").alias("asg")))
query("o_embedding_map", on("gd", f"SELECT unnest([1, 2, 3]) AS u, unnest([m1, m2, m3]) AS vid FROM ({to_sql(ABC)})"))(lambda s, d: joins.as_map(joins.join_match(graph("gd", s, d), ABC)).select(F.explode("mapping").alias("u", "vid")))
query("o_triangle_per_vertex", on("gd", f"SELECT m1 AS vid, count(*) AS triangles FROM ({to_sql(ABC)}) GROUP BY m1"))(lambda s, d: joins.join_match(graph("gd", s, d), ABC).groupBy(F.col("m1").alias("vid")).agg(count_all().alias("triangles")))
_ES = cycle("es", "es", "es")
query("o_distinct_images", on("gk", f"SELECT DISTINCT array_to_string(list_sort([m1, m2, m3]), ',') AS image FROM ({to_sql(_ES)})"))(lambda s, d: joins.distinct_images(joins.join_match(graph("gk", s, d), _ES)).select(F.array_join("image", ",").alias("image")))

# Windows of activity: the same plan for a table and for a stream.
_started = lambda df: df.select("event_type", F.unix_seconds("w.start").alias("start"), "n")
query("o_window_tumbling", "SELECT event_type, epoch_us(ts) // 600000000 * 600 AS start, count(*) AS n FROM events GROUP BY ALL")(lambda s, d: _started(deltas.windowed_activity(src.table(s, d, "events"))))
query("o_window_sliding", "SELECT event_type, (epoch_us(ts) // 300000000 - k) * 300 AS start, count(*) AS n FROM events CROSS JOIN (VALUES (0), (1)) AS o(k) GROUP BY ALL")(lambda s, d: _started(deltas.windowed_activity(src.table(s, d, "events"), "sliding")))
query(
    "o_window_session",
    """WITH moments AS (SELECT event_type, epoch_us(ts) AS us FROM events),
gaps AS (SELECT event_type, us, CASE WHEN us - lag(us) OVER (PARTITION BY event_type ORDER BY us) <= 600000000 THEN 0 ELSE 1 END AS fresh FROM moments),
runs AS (SELECT event_type, us, sum(fresh) OVER (PARTITION BY event_type ORDER BY us ROWS UNBOUNDED PRECEDING) AS run FROM gaps)
SELECT event_type, min(us) // 1000000 AS start, count(*) AS n FROM runs GROUP BY event_type, run""",
)(lambda s, d: _started(deltas.windowed_activity(src.table(s, d, "events"), "session")))


@query("o_delta_match", on("gd", f"SELECT m1, m2, m3 FROM ({to_sql(ABC)}) WHERE (m1 + m2) % 4 = 0 OR (m2 + m3) % 4 = 0 OR (m1 + m3) % 4 = 0"))
def o_delta_match(spark, sf_dir):
    """Edges whose ends sum to a multiple of 4 arrive later: exactly the embeddings on such an edge are new."""
    g = graph("gd", spark, sf_dir)
    late = (F.col("src") + F.col("dst")) % 4 == 0
    return deltas.delta_match(LabeledGraph(g.vertices, g.edges.filter(~late)), g.edges.filter(late & (F.col("src") < F.col("dst"))).select(F.col("src").alias("a"), F.col("dst").alias("b")), ABC)
