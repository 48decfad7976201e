"""Lenses: relational tables as triples.

A lens is a list of projections (subject, predicate, object) over one table, in SQL that Spark and DuckDB both read,
so every workload can be checked against the other engine.  ``{explode}`` stands for the engine's own function.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..vocab import VOCAB

TYPE = VOCAB.type

_HOST = "regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1)"
_UP1 = f"regexp_replace({_HOST}, '^[^.]+[.]', '')"
_UP2 = f"regexp_replace({_UP1}, '^[^.]+[.]', '')"


def _id(kind: str, column: str) -> str:
    return f"'{kind}/' || CAST({column} AS STRING)"


#: Per table: subject, predicate, object, and a condition or a source in place of the table.
LENSES: dict[str, list[tuple[str, str, str, str]]] = {
    "region": [(_id("region", "r_regionkey"), TYPE, "'class/Region'", "")],
    "nation": [
        (_id("nation", "n_nationkey"), "inRegion", _id("region", "n_regionkey"), ""),
        (_id("nation", "n_nationkey"), TYPE, "'class/Nation'", ""),
        (_id("nation", "k"), "neighbourOf", _id("nation", "l"), "(SELECT n_nationkey AS k, lead(n_nationkey) OVER (PARTITION BY n_regionkey ORDER BY n_nationkey) AS l FROM nation) x WHERE l IS NOT NULL"),
    ],
    "customer": [
        (_id("customer", "c_custkey"), "inNation", _id("nation", "c_nationkey"), ""),
        (_id("customer", "c_custkey"), TYPE, "'class/segment/' || c_mktsegment", ""),
    ],
    "supplier": [
        (_id("supplier", "s_suppkey"), "inNation", _id("nation", "s_nationkey"), ""),
        (_id("supplier", "s_suppkey"), TYPE, "'class/Supplier'", ""),
    ],
    "part": [
        (_id("part", "p_partkey"), TYPE, "'class/ptype/' || p_type", ""),
        (_id("part", "p_partkey"), TYPE, "'class/noun/' || split_part(p_name, ' ', 2)", ""),
        (_id("part", "p_partkey"), "hasBrand", "'brand/' || p_brand", ""),
    ],
    "orders": [
        (_id("order", "o_orderkey"), "placedBy", _id("customer", "o_custkey"), ""),
        (_id("order", "o_orderkey"), TYPE, "'class/priority/' || o_orderpriority", ""),
        (_id("order", "o_orderkey"), "hasStatus", "'status/' || o_orderstatus", ""),
    ],
    "lineitem": [
        (_id("order", "l_orderkey"), "containsPart", _id("part", "l_partkey"), ""),
        (_id("order", "l_orderkey"), "shippedBy", _id("supplier", "l_suppkey"), ""),
        (_id("part", "l_partkey"), "offeredBy", _id("supplier", "l_suppkey"), "(SELECT DISTINCT l_partkey, l_suppkey FROM lineitem) x"),
    ],
    "events": [
        (_id("event", "k"), "nextEvent", _id("event", "l"), "(SELECT event_id AS k, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS l FROM events) x WHERE l IS NOT NULL"),
        (_id("event", "event_id"), "doneBy", _id("user", "user_id"), ""),
        (_id("event", "event_id"), TYPE, "'class/event/' || event_type", ""),
    ],
    "documents": [
        (_id("doc", "doc_id"), "hasText", "'text/' || md5(text)", ""),
        (_id("doc", "doc_id"), "fromSource", "'source/' || source", ""),
        (_id("doc", "doc_id"), "inLanguage", "'lang/' || lang", ""),
    ],
    "labels": [
        (_id("doc", "doc_id"), TYPE, "'class/HighQuality'", "labels WHERE quality = 1"),
        (_id("doc", "doc_id"), TYPE, "'class/Toxic'", "labels WHERE toxic = 1"),
    ],
    "pages": [
        (_id("page", "page_id"), "onHost", f"'host/' || {_HOST}", ""),
        (f"'host/' || {_HOST}", "subdomainOf", f"'host/' || {_UP1}", f"pages WHERE {_HOST} LIKE '%.%.%'"),
        (f"'host/' || {_UP1}", "subdomainOf", f"'host/' || {_UP2}", f"pages WHERE {_HOST} LIKE '%.%.%.%'"),
        (_id("page", "page_id"), "linksTo", "'path/' || h", "(SELECT page_id, {explode}(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS h FROM pages) x"),
    ],
    "conversations": [
        ("'turn/' || CAST(conv_id AS STRING) || '/' || CAST(turn AS STRING)", "repliesTo", "'turn/' || CAST(conv_id AS STRING) || '/' || CAST(turn - 1 AS STRING)", "conversations WHERE turn > 0"),
        ("'turn/' || CAST(conv_id AS STRING) || '/' || CAST(turn AS STRING)", "inConversation", _id("conv", "conv_id"), ""),
        ("'turn/' || CAST(conv_id AS STRING) || '/' || CAST(turn AS STRING)", TYPE, "'class/role/' || role", ""),
    ],
    "embeddings": [(_id("vec", "vec_id"), TYPE, "'class/cluster/' || CAST(label AS STRING)", "")],
    "benchmark": [
        (_id("item", "item_id"), TYPE, "'class/BenchmarkItem'", ""),
        (_id("item", "item_id"), "hasText", "'text/' || md5(text)", ""),
    ],
}
TABLES = tuple(LENSES)


def projections(tables=TABLES, predicates: tuple[str, ...] | None = None, explode: str = "unnest") -> list[str]:
    """SELECT statements of the lenses, of all predicates or of those named."""
    out = []
    for t in tables:
        for s, p, o, source in LENSES[t]:
            if predicates is None or p in predicates:
                out.append(f"SELECT {s} AS s, '{p}' AS p, {o} AS o FROM {source or t}".replace("{explode}", explode))
    return out


def lens_sql(tables=TABLES, predicates: tuple[str, ...] | None = None) -> str:
    """The triples in DuckDB's SQL, as a set."""
    return " UNION ".join(projections(tables, predicates))


def bag_sql(tables=TABLES, predicates: tuple[str, ...] | None = None) -> str:
    """The triples as they come, repeats included."""
    return " UNION ALL ".join(projections(tables, predicates))


def bag(spark: SparkSession, sf_dir: str, tables=TABLES, predicates: tuple[str, ...] | None = None) -> DataFrame:
    """The triples as they come from the tables; scans read only the columns of the projections."""
    texts = projections(tables, predicates, "explode")
    used = [t for t in tables if any(f" {t}" in x for x in texts)]
    frames = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in used}
    out = None
    for text in texts:
        own = next(t for t in tables if f"FROM {t}" in text)
        # A name bound to a frame, not a session-wide view: lenses over different folders don't meet.
        one = spark.sql(text.replace("{", "{{").replace("}", "}}").replace(f"FROM {own}", "FROM {own}"), own=frames[own])
        out = one if out is None else out.union(one)
    return out


def lens(spark: SparkSession, sf_dir: str, tables=TABLES, predicates: tuple[str, ...] | None = None) -> DataFrame:
    """The triples of the tables, as a set."""
    return bag(spark, sf_dir, tables, predicates).distinct()
