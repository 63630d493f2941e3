"""Graphs over the given tables, each with the SQL that builds the same edges in DuckDB."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from hubgraph.core.model import PropertyGraph
from hubgraph.core.portable import bits, sql_bits
from hubgraph.session import table

TYPE = 1 << 40
_DAYS = "date_diff('day', DATE '1970-01-01', l_shipdate::DATE)"
_KEY = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
_ETYPE = "CASE concat(l_returnflag, l_linestatus) WHEN 'RF' THEN 0 WHEN 'AF' THEN 1 WHEN 'NF' THEN 2 WHEN 'NO' THEN 3 ELSE 4 END"


def _lines(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select(*_KEY, "l_quantity", "l_returnflag", "l_linestatus", "l_shipdate")
    return lines.withColumn("eid", bits("e", *_KEY, F.datediff("l_shipdate", F.lit("1970-01-01").cast("date")), digits=15))


def trade(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Part to supplier, an edge for each line: nearly regular."""
    edges = _lines(spark, sf_dir).select("eid", F.col("l_partkey").alias("src"), (F.lit(TYPE) + F.col("l_suppkey")).alias("dst"), F.expr(_ETYPE).alias("etype"), F.col("l_quantity").alias("weight"))
    return PropertyGraph("trade", edges)


def folded(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """The same lines with keys folded by a cube, which makes extreme hubs."""

    def fold(key, n):
        return F.expr(f"({key} * {key} * {key}) div ({n} * {n})")

    parts, suppliers = (table(spark, sf_dir, t).count() for t in ("part", "supplier"))
    edges = _lines(spark, sf_dir).select("eid", fold("l_partkey", f"{parts}L").alias("src"), (F.lit(TYPE) + fold("l_suppkey", f"{suppliers}L")).alias("dst"), F.expr(_ETYPE).alias("etype"), F.col("l_quantity").alias("weight"))
    return PropertyGraph("folded", edges)


def lexicon(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Document to token, distinct pairs: naturally a power law. Texts meet by id, which moves less than their pairs would."""
    texts = table(spark, sf_dir, "documents").groupBy("doc_id").agg(F.collect_set("text").alias("texts"))
    tokens = F.array_distinct(F.flatten(F.transform("texts", lambda x: F.split(F.lower(x), "[^a-zà-ÿ]+"))))
    pairs = texts.select("doc_id", F.explode(tokens).alias("token")).where("token <> ''")
    edges = pairs.select(bits("e", "doc_id", "token", digits=15).alias("eid"), F.col("doc_id").alias("src"), (F.lit(TYPE) + bits("t", "token", digits=14)).alias("dst"), F.lit(0).alias("etype"), F.lit(1.0).alias("weight"))
    return PropertyGraph("lexicon", edges)


#: Commerce edge types: name, table, source type and key, target type and key.
COMMERCE = (
    ("orders", "orders", 0, "o_custkey", 1, "o_orderkey"), ("holds", "lineitem", 1, "l_orderkey", 2, "l_partkey"), ("from", "lineitem", 1, "l_orderkey", 3, "l_suppkey"),
    ("lives", "customer", 0, "c_custkey", 4, "c_nationkey"), ("sits", "supplier", 3, "s_suppkey", 4, "s_nationkey"), ("in", "nation", 4, "n_nationkey", 5, "n_regionkey"),
)


def commerce(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Six vertex types and six edge types."""
    edges = None
    for k, (_, name, a, source, b, target) in enumerate(COMMERCE):
        part = table(spark, sf_dir, name).select((F.lit(a * TYPE) + F.col(source)).cast("long").alias("src"), (F.lit(b * TYPE) + F.col(target)).cast("long").alias("dst"), F.lit(k).alias("etype"), F.lit(1.0).alias("weight"))
        if name == "lineitem":
            part = part.distinct()
        edges = part if edges is None else edges.union(part)
    return PropertyGraph("commerce", edges.select(bits("e", "etype", "src", "dst", digits=15).alias("eid"), "src", "dst", "etype", "weight"))


def activity(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """User to the k of the event's properties, typed by event, with time and value."""
    e = table(spark, sf_dir, "events")
    return PropertyGraph("activity", e.select(F.col("event_id").alias("eid"), F.col("user_id").alias("src"), (F.lit(TYPE) + F.get_json_object("props", "$.k").cast("long")).alias("dst"), (F.ascii("event_type") % 7).alias("etype"), F.col("value").alias("weight"), "ts"))


def dialog(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Each turn to its role, and to the next turn: chains and a few extreme hubs."""
    t = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1024 + F.col("turn")).alias("src"), "role")
    hub = t.select("src", (F.lit(TYPE) + F.ascii("role")).cast("long").alias("dst"), F.lit(0).alias("etype"))
    chain = t.alias("a").join(t.select(F.col("src").alias("dst")), F.col("dst") == F.col("a.src") + 1).select("src", "dst", F.lit(1).alias("etype"))
    edges = hub.union(chain)
    return PropertyGraph("dialog", edges.select(bits("e", "etype", "src", "dst", digits=15).alias("eid"), "src", "dst", "etype", F.lit(1.0).alias("weight")))


def web(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Page to host, and to the targets of its links: distinct pairs, skewed by host."""
    p = table(spark, sf_dir, "pages").select(F.col("page_id").alias("src"), "url", "html")
    host = p.select("src", (F.lit(TYPE) + bits("w", F.regexp_extract("url", _HOST, 1), digits=9)).alias("dst"), F.lit(0).alias("etype"))
    link = p.select("src", F.explode(F.regexp_extract_all("html", F.lit(_HREF), 1)).alias("to")).select("src", (F.lit(2 * TYPE) + bits("w", "to", digits=9)).alias("dst"), F.lit(1).alias("etype"))
    edges = host.union(link).distinct()
    return PropertyGraph("web", edges.select(bits("e", "etype", "src", "dst", digits=15).alias("eid"), "src", "dst", "etype", F.lit(1.0).alias("weight")))


_HOST, _HREF = "^[a-z]+://([^/]+)", 'href="([^"]*)"'
GRAPHS = {"trade": trade, "folded": folded, "lexicon": lexicon, "commerce": commerce, "activity": activity, "dialog": dialog, "web": web}

_LINE_EID = sql_bits("e", *_KEY, _DAYS, digits=15)
_COMMERCE_SQL = " UNION ALL ".join(f"SELECT {'DISTINCT' if name == 'lineitem' else ''} {a * TYPE} + {s}::BIGINT AS src, {b * TYPE} + {t}::BIGINT AS dst, {k} AS etype FROM {name}" for k, (_, name, a, s, b, t) in enumerate(COMMERCE))
SQL = {
    "trade": f"SELECT {_LINE_EID} AS eid, l_partkey AS src, {TYPE} + l_suppkey AS dst, {_ETYPE} AS etype, l_quantity AS weight FROM lineitem",
    "folded": f"SELECT {_LINE_EID} AS eid, (l_partkey * l_partkey * l_partkey) // (p.n * p.n) AS src, {TYPE} + (l_suppkey * l_suppkey * l_suppkey) // (s.n * s.n) AS dst, {_ETYPE} AS etype, l_quantity AS weight FROM lineitem, (SELECT count(*) AS n FROM part) p, (SELECT count(*) AS n FROM supplier) s",
    "lexicon": f"SELECT {sql_bits('e', 'doc_id', 'token', digits=15)} AS eid, doc_id AS src, {TYPE} + {sql_bits('t', 'token', digits=14)} AS dst, 0 AS etype, 1.0::DOUBLE AS weight FROM (SELECT DISTINCT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-zà-ÿ]+')) AS token FROM documents) WHERE token <> ''",
    "commerce": f"SELECT {sql_bits('e', 'etype', 'src', 'dst', digits=15)} AS eid, src, dst, etype, 1.0::DOUBLE AS weight FROM ({_COMMERCE_SQL})",
}

_ROLE_SQL = f"SELECT conv_id * 1024 + turn AS src, {TYPE} + ascii(role) AS dst, 0 AS etype FROM conversations UNION ALL SELECT a.src, b.dst, 1 FROM (SELECT conv_id * 1024 + turn AS src FROM conversations) a JOIN (SELECT conv_id * 1024 + turn AS dst FROM conversations) b ON b.dst = a.src + 1"
_WEB_SQL = f"SELECT page_id AS src, {TYPE} + {sql_bits('w', f"regexp_extract(url, '{_HOST}', 1)", digits=9)} AS dst, 0 AS etype FROM pages UNION SELECT src, {2 * TYPE} + {sql_bits('w', 'target', digits=9)}, 1 FROM (SELECT page_id AS src, unnest(regexp_extract_all(html, '{_HREF}', 1)) AS target FROM pages)"
#: Graphs that only statistics and hash placements run over.
MORE_SQL = {
    "activity": f"SELECT event_id AS eid, user_id AS src, {TYPE} + CAST(json_extract(props, '$.k') AS BIGINT) AS dst, ascii(event_type) % 7 AS etype, value AS weight FROM events",
    "dialog": f"SELECT {sql_bits('e', 'etype', 'src', 'dst', digits=15)} AS eid, src, dst, etype, 1.0::DOUBLE AS weight FROM ({_ROLE_SQL})",
    "web": f"SELECT {sql_bits('e', 'etype', 'src', 'dst', digits=15)} AS eid, src, dst, etype, 1.0::DOUBLE AS weight FROM ({_WEB_SQL})",
}
