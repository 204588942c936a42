"""Data graphs built from the given tables, each beside the SQL of its views v(vid, label) and e(src, dst)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from branchwise.operators.graph import LabeledGraph
from branchwise.plans.pattern import QUERY_SET
from branchwise.plans.sqlgen import LABELLED

#: Ids of graphs with several kinds of vertices: kind * 2^48 + key.
KIND = 1 << 48
_HALF = "l_quantity <= 25"
RULES = {"order": [], "flag": ["l_returnflag"], "flag_half": ["l_returnflag", "l_linestatus", _HALF]}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def part_pairs(spark: SparkSession, sf_dir: str, rule: str = "flag", label: str = "p_brand", loops: bool = False) -> LabeledGraph:
    """Parts that share an order, and by the rule also flags or the side of a quantity. loops: a part that an order has twice has
    an edge to itself."""
    keys = [F.expr(k).alias(f"k{i}") for i, k in enumerate(["l_orderkey", *RULES[rule]])]
    rows = table(spark, sf_dir, "lineitem").select(*keys, F.col("l_partkey").alias("p")).distinct()
    names = [f"k{i}" for i in range(len(keys))]
    pairs = rows.withColumnRenamed("p", "a").join(rows.withColumnRenamed("p", "b"), names).filter("a < b").select("a", "b")
    if loops:
        twice = table(spark, sf_dir, "lineitem").groupBy("l_orderkey", F.col("l_partkey").alias("a")).count().filter("count > 1")
        pairs = pairs.unionByName(twice.select("a", F.col("a").alias("b")))
    return LabeledGraph.from_edges(table(spark, sf_dir, "part").select(F.col("p_partkey").alias("vid"), F.expr(label).alias("label")), pairs, loops=loops)


_MIRROR = "e AS MATERIALIZED (SELECT a AS src, b AS dst FROM pairs UNION ALL SELECT b, a FROM pairs)"


def part_pairs_sql(rule: str = "flag", label: str = "p_brand", loops: bool = False) -> str:
    keys = ["l_orderkey", *RULES[rule]]
    cols = ", ".join(f"{k} AS k{i}" for i, k in enumerate(keys))
    on = ", ".join(f"k{i}" for i in range(len(keys)))
    twice = "loops AS MATERIALIZED (SELECT DISTINCT l_partkey AS vid FROM (SELECT l_orderkey, l_partkey FROM lineitem GROUP BY ALL HAVING count(*) > 1)),\n" if loops else ""
    return f"""WITH li AS MATERIALIZED (SELECT DISTINCT {cols}, l_partkey AS p FROM lineitem),
pairs AS MATERIALIZED (SELECT DISTINCT x.p AS a, y.p AS b FROM li x JOIN li y USING ({on}) WHERE x.p < y.p),
{twice}{_MIRROR}, v AS MATERIALIZED (SELECT p_partkey AS vid, CAST({label} AS VARCHAR) AS label FROM part), {LABELLED}"""


def trade_entities(spark: SparkSession, sf_dir: str, order_label: str = "'order'", part_label: str = "'part'") -> LabeledGraph:
    """Customers 1, orders 2, parts 3, suppliers 4, nations 5, regions 6, joined by their keys."""
    t = lambda n: table(spark, sf_dir, n)
    vid = lambda kind, c: (F.lit(kind * KIND) + F.col(c)).alias("vid")
    parts = [
        t("customer").select(vid(1, "c_custkey"), F.lit("customer").alias("label")), t("orders").select(vid(2, "o_orderkey"), F.expr(order_label).alias("label")),
        t("part").select(vid(3, "p_partkey"), F.expr(part_label).alias("label")), t("supplier").select(vid(4, "s_suppkey"), F.lit("supplier").alias("label")),
        t("nation").select(vid(5, "n_nationkey"), F.lit("nation").alias("label")), t("region").select(vid(6, "r_regionkey"), F.lit("region").alias("label")),
    ]
    pair = lambda df, ka, a, kb, b: df.select((F.lit(ka * KIND) + F.col(a)).alias("a"), (F.lit(kb * KIND) + F.col(b)).alias("b"))
    li = t("lineitem")
    pairs = [
        pair(t("orders"), 2, "o_orderkey", 1, "o_custkey"), pair(li, 2, "l_orderkey", 3, "l_partkey"), pair(li, 2, "l_orderkey", 4, "l_suppkey"),
        pair(t("customer"), 1, "c_custkey", 5, "c_nationkey"), pair(t("supplier"), 4, "s_suppkey", 5, "s_nationkey"), pair(t("nation"), 5, "n_nationkey", 6, "n_regionkey"),
    ]
    whole = lambda dfs: dfs[0] if len(dfs) == 1 else whole([dfs[0].unionByName(dfs[1]), *dfs[2:]])
    return LabeledGraph.from_edges(whole(parts), whole(pairs))


def trade_entities_sql(order_label: str = "'order'", part_label: str = "'part'") -> str:
    k = KIND
    return f"""WITH v AS MATERIALIZED (SELECT {k} + c_custkey AS vid, 'customer' AS label FROM customer UNION ALL SELECT {2 * k} + o_orderkey, {order_label} FROM orders
UNION ALL SELECT {3 * k} + p_partkey, {part_label} FROM part UNION ALL SELECT {4 * k} + s_suppkey, 'supplier' FROM supplier
UNION ALL SELECT {5 * k} + n_nationkey, 'nation' FROM nation UNION ALL SELECT {6 * k} + r_regionkey, 'region' FROM region),
pairs AS MATERIALIZED (SELECT {2 * k} + o_orderkey AS a, {k} + o_custkey AS b FROM orders UNION SELECT {2 * k} + l_orderkey, {3 * k} + l_partkey FROM lineitem
UNION SELECT {2 * k} + l_orderkey, {4 * k} + l_suppkey FROM lineitem UNION SELECT {k} + c_custkey, {5 * k} + c_nationkey FROM customer
UNION SELECT {4 * k} + s_suppkey, {5 * k} + s_nationkey FROM supplier UNION SELECT {5 * k} + n_nationkey, {6 * k} + n_regionkey FROM nation), {_MIRROR}, {LABELLED}"""


def vector_proximity(spark: SparkSession, sf_dir: str, threshold: float = 0.3, block: int = 2048) -> LabeledGraph:
    """Vectors with a cosine of at least the threshold. All pairs are compared, block against block, by matrix products in tasks;
    only pairs above the threshold leave them. A cosine of 0.3 is an angle of 73 degrees: no pivot or range of angles
    excludes a pair exactly there, so that a vector meets every block (one copy per ``block`` vectors)."""
    import numpy as np
    import pandas as pd

    rows = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    blocks = max(1, -(-rows.count() // block))
    own = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    dealt = rows.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumns({"lo": F.least("own", "other"), "hi": F.greatest("own", "other")})

    def near(part: pd.DataFrame) -> pd.DataFrame:
        x = np.array(part["x"].tolist(), float)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        ids, own = part["vec_id"].to_numpy(), part["own"].to_numpy()
        ok = (x @ x.T >= threshold) & (ids[:, None] < ids[None, :])
        if part["lo"].iat[0] != part["hi"].iat[0]:
            ok &= own[:, None] != own[None, :]
        i, j = np.nonzero(ok)
        return pd.DataFrame({"a": ids[i], "b": ids[j]})

    pairs = dealt.groupBy("lo", "hi").applyInPandas(near, "a bigint, b bigint")
    return LabeledGraph.from_edges(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("vid"), F.col("label").cast("string").alias("label")), pairs)


def vector_proximity_sql(threshold: float = 0.3) -> str:
    return f"""WITH x AS MATERIALIZED (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings),
pairs AS MATERIALIZED (SELECT p.vec_id AS a, q.vec_id AS b FROM x p JOIN x q ON p.vec_id < q.vec_id WHERE list_cosine_similarity(p.x, q.x) >= {threshold}),
{_MIRROR}, v AS MATERIALIZED (SELECT vec_id AS vid, CAST(label AS VARCHAR) AS label FROM embeddings), {LABELLED}"""


def user_pairs(events: DataFrame, seconds: int = 20, salts: int = 4) -> DataFrame:
    """Users with the same event type at most so many seconds apart: equal or neighbouring time slots, then the exact test.
    One side of a slot is dealt over salts, the other is there for each, so that a busy slot is several tasks."""
    micros = F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast(ts AS timestamp_ntz))")
    slot = F.floor(F.col("at") / (seconds * 1_000_000))
    rows = events.select("user_id", "event_type", micros.alias("at")).withColumns({"slot": slot, "salt": F.pmod(F.xxhash64("user_id", "at"), F.lit(salts)).cast("int")})
    near = rows.select(F.col("user_id").alias("b"), "event_type", F.col("at").alias("at_b"), F.explode(F.array(F.col("slot") - 1, "slot", F.col("slot") + 1)).alias("slot")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    apart = F.abs(F.col("at") - F.col("at_b")) <= seconds * 1_000_000
    return rows.join(near, ["event_type", "slot", "salt"]).filter(apart & (F.col("user_id") < F.col("b"))).select(F.col("user_id").alias("a"), "b").distinct()


def user_labels(events: DataFrame) -> DataFrame:
    by = events.groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return by.groupBy("user_id").agg(F.min_by("event_type", F.struct(-F.col("n"), F.col("event_type"))).alias("label")).withColumnRenamed("user_id", "vid")


def user_proximity(spark: SparkSession, sf_dir: str, seconds: int = 20) -> LabeledGraph:
    events = table(spark, sf_dir, "events")
    return LabeledGraph.from_edges(user_labels(events), user_pairs(events, seconds))


def user_proximity_sql(seconds: int = 20) -> str:
    us = seconds * 1_000_000
    return f"""WITH by_type AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL),
v AS MATERIALIZED (SELECT user_id AS vid, event_type AS label FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY n DESC, event_type) AS r FROM by_type) WHERE r = 1),
moments AS MATERIALIZED (SELECT user_id, event_type, epoch_us(ts) AS us, epoch_us(ts) // {us} AS slot FROM events),
near AS MATERIALIZED (SELECT user_id, event_type, us, slot + d AS slot FROM moments CROSS JOIN (VALUES (-1), (0), (1)) AS o(d)),
pairs AS MATERIALIZED (SELECT DISTINCT x.user_id AS a, y.user_id AS b FROM moments x JOIN near y ON x.event_type = y.event_type AND x.slot = y.slot WHERE x.user_id < y.user_id AND abs(x.us - y.us) <= {us}), {_MIRROR}, {LABELLED}"""


def shared_lines(spark: SparkSession, sf_dir: str, min_len: int = 40, max_docs: int = 50, label: str = "lang") -> LabeledGraph:
    """Documents that share a trimmed line of some length which 2 to max_docs documents have."""
    docs = table(spark, sf_dir, "documents")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).filter(F.length("line") >= min_len).distinct()
    some = lines.groupBy("line").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n").between(2, max_docs)).select("line")
    kept = lines.join(some, "line")
    pairs = kept.withColumnRenamed("doc_id", "a").join(kept.withColumnRenamed("doc_id", "b"), "line").filter("a < b").select("a", "b")
    return LabeledGraph.from_edges(docs.select(F.col("doc_id").alias("vid"), F.expr(label).alias("label")), pairs)


def shared_lines_sql(min_len: int = 40, max_docs: int = 50, label: str = "lang") -> str:
    return f"""WITH lines AS MATERIALIZED (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, trim(unnest(string_split(text, chr(10))), ' ') AS line FROM documents) WHERE length(line) >= {min_len}),
few AS MATERIALIZED (SELECT line FROM lines GROUP BY line HAVING count(*) BETWEEN 2 AND {max_docs}), kept AS MATERIALIZED (SELECT lines.* FROM lines JOIN few ON few.line = lines.line),
pairs AS MATERIALIZED (SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM kept x JOIN kept y USING (line) WHERE x.doc_id < y.doc_id),
{_MIRROR}, v AS MATERIALIZED (SELECT doc_id AS vid, {label} AS label FROM documents), {LABELLED}"""


def document_lines(spark: SparkSession, sf_dir: str, min_len: int = 40, label: str = "lang") -> LabeledGraph:
    """Documents and the trimmed lines of some length that several documents have, however many: two documents share a line
    where a path of length two joins them. Edges grow with the text and not with the square of a common line's documents."""
    docs = table(spark, sf_dir, "documents")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).filter(F.length("line") >= min_len).distinct()
    some = lines.groupBy("line").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("line")
    ends = lines.join(some, "line").select((F.lit(KIND) + F.col("doc_id")).alias("a"), (F.lit(2 * KIND) + _name_key("line")).alias("b"))
    vertices = docs.select((F.lit(KIND) + F.col("doc_id")).alias("vid"), F.expr(label).alias("label"))
    return LabeledGraph.from_edges(vertices.unionByName(ends.select(F.col("b").alias("vid"), F.lit("line").alias("label")).distinct()), ends)


def document_lines_sql(min_len: int = 40, label: str = "lang") -> str:
    return f"""WITH lines AS MATERIALIZED (SELECT DISTINCT doc_id, line AS name FROM (SELECT doc_id, trim(unnest(string_split(text, chr(10))), ' ') AS line FROM documents) WHERE length(line) >= {min_len}),
held AS MATERIALIZED (SELECT name FROM lines GROUP BY name HAVING count(*) > 1),
pairs AS MATERIALIZED (SELECT DISTINCT {KIND} + doc_id AS a, {2 * KIND} + {_NAME_KEY_SQL} AS b FROM lines JOIN held USING (name)),
{_MIRROR}, v AS MATERIALIZED (SELECT {KIND} + doc_id AS vid, {label} AS label FROM documents UNION ALL SELECT DISTINCT b, 'line' FROM pairs), {LABELLED}"""


def _name_key(name: str):
    """47 bits of a digest: the key of a vertex that has a name but no number."""
    return F.shiftrightunsigned(F.conv(F.substring(F.md5(F.col(name)), 1, 12), 16, 10).cast("bigint"), 1)


_NAME_KEY_SQL = "(CAST('0x' || substr(md5(name), 1, 12) AS BIGINT) >> 1)"


def page_links(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Pages, their hosts and the targets of their links; hosts and targets are numbered by name."""
    pages = table(spark, sf_dir, "pages")
    host = F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1)
    hosts = pages.select("page_id", host.alias("name"))
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).alias("name"))
    vid = lambda kind: F.lit(kind * KIND) + _name_key("name")
    vertices = pages.select("page_id").select((F.lit(KIND) + F.col("page_id")).alias("vid"), F.lit("page").alias("label"))
    vertices = vertices.unionByName(hosts.select(vid(2).alias("vid"), F.lit("host").alias("label")).distinct()).unionByName(links.select(vid(3).alias("vid"), F.lit("href").alias("label")).distinct())
    page = (F.lit(KIND) + F.col("page_id")).alias("a")
    return LabeledGraph.from_edges(vertices, hosts.select(page, vid(2).alias("b")).unionByName(links.select(page, vid(3).alias("b"))))


def page_links_sql() -> str:
    vid = lambda kind: f"{kind * KIND} + {_NAME_KEY_SQL}"
    return f"""WITH hosts AS MATERIALIZED (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS name FROM pages),
links AS MATERIALIZED (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS name FROM pages),
pairs AS MATERIALIZED (SELECT {KIND} + page_id AS a, {vid(2)} AS b FROM hosts UNION SELECT {KIND} + page_id, {vid(3)} FROM links),
{_MIRROR}, v AS MATERIALIZED (SELECT {KIND} + page_id AS vid, 'page' AS label FROM pages UNION SELECT {vid(2)}, 'host' FROM hosts UNION SELECT {vid(3)}, 'href' FROM links), {LABELLED}"""


def turn_chain(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    turns = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("vid"), "conv_id", "turn", "role")
    after = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("vid").alias("b"))
    return LabeledGraph.from_edges(turns.select("vid", F.col("role").alias("label")), turns.join(after, ["conv_id", "turn"]).select(F.col("vid").alias("a"), "b"))


def turn_chain_sql() -> str:
    return f"""WITH v AS MATERIALIZED (SELECT conv_id * 1000 + turn AS vid, role AS label FROM conversations),
pairs AS MATERIALIZED (SELECT x.conv_id * 1000 + x.turn AS a, y.conv_id * 1000 + y.turn AS b FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND y.turn = x.turn + 1), {_MIRROR}, {LABELLED}"""


def edge_list(spark: SparkSession, vertices_path: str, edges_path: str, fmt: str = "csv", loops: bool = False) -> LabeledGraph:
    """A graph from two files or folders: (vid, label) and (a, b)."""
    read = lambda path, schema: spark.read.format(fmt).schema(schema).option("header", "true").load(path)
    return LabeledGraph.from_edges(read(vertices_path, "vid bigint, label string"), read(edges_path, "a bigint, b bigint"), validate=True, loops=loops)


def table_graph(spark: SparkSession, vertices: str, edges: str, loops: bool = False) -> LabeledGraph:
    """A graph from two tables of the catalog: vid, label and attributes; a and b."""
    return LabeledGraph.from_edges(spark.table(vertices), spark.table(edges).select("a", "b"), validate=True, loops=loops)


def pattern_file(spark: SparkSession, path: str) -> DataFrame:
    """A query set from JSON lines: labels, an array by vertex, and edges, an array of pairs of numbers; query_id by rising
    place of the file, unless it is given."""
    rows = spark.read.schema("query_id int, labels array<string>, edges array<array<int>>").json(path)
    number = F.coalesce("query_id", (F.row_number().over(Window.orderBy(F.monotonically_increasing_id())) - 1).cast("int"))  # patterns are few
    vertices = F.transform("labels", lambda x, i: F.struct((i + 1).alias("u"), x.alias("label")))
    pairs = F.transform("edges", lambda e: F.struct(e[0].alias("a"), e[1].alias("b")))
    out = rows.select(number.alias("query_id"), F.size("labels").alias("n_vertices"), vertices.alias("vertices"), pairs.alias("edges"), F.sequence(F.lit(1), F.size("labels")).alias("match_order"))
    return out.to(spark.createDataFrame([], QUERY_SET).schema)
