"""The local ontology over the lens's terms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..triples import TRIPLE
from ..vocab import VOCAB as V

#: Schema triples that do not depend on data.  Fixed values.
FIXED: list[tuple[str, str, str]] = [
    # classes
    ("class/Part", V.sub_class, "class/Product"),
    ("class/Product", V.sub_class, "class/Thing"),
    ("class/Customer", V.sub_class, "class/Agent"),
    ("class/Agent", V.sub_class, "class/Thing"),
    ("class/Supplier", V.sub_class, "class/Agent"),
    ("class/Client", V.equivalent_class, "class/Customer"),
    ("class/Order", V.sub_class, "class/Purchase"),
    ("class/Purchase", V.sub_class, "class/Order"),
    # properties
    ("inNation", V.sub_property, "locatedIn"),
    ("inRegion", V.sub_property, "locatedIn"),
    ("nextEvent", V.sub_property, "precedes"),
    ("repliesTo", V.sub_property, "inThread"),
    ("subdomainOf", V.sub_property, "under"),
    ("placedBy", V.sub_property, "involves"),
    ("shippedBy", V.sub_property, "involves"),
    ("involves", V.sub_property, "related"),
    ("promotedIn", V.sub_property, "featuredIn"),
    ("soldBy", V.equivalent_property, "shippedBy"),
    ("offeredBy", V.sub_property, "suppliedBy"),
    ("suppliedBy", V.sub_property, "offeredBy"),
    # domains and ranges
    ("placedBy", V.domain, "class/Order"),
    ("placedBy", V.range, "class/Customer"),
    ("containsPart", V.domain, "class/Order"),
    ("containsPart", V.range, "class/Part"),
    ("doneBy", V.domain, "class/Event"),
    ("doneBy", V.range, "class/User"),
    # traits
    ("locatedIn", V.type, V.transitive),
    ("precedes", V.type, V.transitive),
    ("inThread", V.type, V.transitive),
    ("under", V.type, V.transitive),
    ("neighbourOf", V.type, V.symmetric),
    ("carriedBy", V.type, V.functional),
    ("hasText", V.type, V.inverse_functional),
    # inverses
    ("placedBy", V.inverse, "placed"),
    ("hasText", V.inverse, "carriedBy"),
    ("offeredBy", V.inverse, "offers"),
    # restrictions
    ("class/InRegion3", V.on_property, "locatedIn"),
    ("class/InRegion3", V.has_value, "region/3"),
    ("class/PromoItem", V.on_property, "promotedIn"),
    ("class/PromoItem", V.has_value, "campaign/spring"),
    ("class/ptype/PROMO", V.sub_class, "class/PromoItem"),
    ("class/UrgentBuyer", V.on_property, "placed"),
    ("class/UrgentBuyer", V.some_values, "class/priority/1-URGENT"),
    ("class/AuditedOrder", V.on_property, "shippedBy"),
    ("class/AuditedOrder", V.all_values, "class/AuditedSupplier"),
    ("class/priority/2-HIGH", V.sub_class, "class/AuditedOrder"),
]

#: Merging rules are off by default; these triples feed them.
MERGING: list[tuple[str, str, str]] = [
    ("class/Item", V.type, V.class_term),
    ("class/Item", V.identity, "class/Part"),
    ("sells", V.type, V.property_term),
    ("sells", V.identity, "offers"),
]

#: Leaf classes found in data: prefix, expression, table, parent.
_LEAVES = [
    ("class/ptype/", "p_type", "part", "class/Part"),
    ("class/segment/", "c_mktsegment", "customer", "class/Customer"),
    ("class/priority/", "o_orderpriority", "orders", "class/Order"),
    ("class/event/", "event_type", "events", "class/Event"),
    ("class/role/", "role", "conversations", "class/Turn"),
    ("class/cluster/", "CAST(label AS STRING)", "embeddings", "class/Vector"),
]


def values_sql(rows: list[tuple[str, str, str]]) -> str:
    return "SELECT * FROM (VALUES " + ", ".join(f"('{s}', '{p}', '{o}')" for s, p, o in rows) + ") AS v(s, p, o)"


def leaf_sql(tables=None) -> list[tuple[str, str]]:
    return [(t, f"SELECT DISTINCT '{prefix}' || {e} AS s, '{V.sub_class}' AS p, '{parent}' AS o FROM {t}") for prefix, e, t, parent in _LEAVES if tables is None or t in tables]


def ontology_sql(tables=None, merging: bool = False) -> str:
    """The ontology in DuckDB's SQL, with the leaf classes of ``tables``."""
    return " UNION ".join([values_sql(FIXED + (MERGING if merging else [])), *(q for _, q in leaf_sql(tables))])


def ontology(spark: SparkSession, sf_dir: str, tables=None, merging: bool = False) -> DataFrame:
    out = spark.createDataFrame(FIXED + (MERGING if merging else []), TRIPLE)
    for t, q in leaf_sql(tables):
        out = out.union(spark.sql(q.replace(f"FROM {t}", "FROM {own}"), own=spark.read.parquet(f"{sf_dir}/{t}.parquet")))
    return out.distinct()
