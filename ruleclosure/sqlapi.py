"""The SQL surface: reasoning over a view, results as views."""

from __future__ import annotations

from pyspark.sql import SparkSession

from .functions.terms import ExpandClique, HtmlLinks, parse_ntriple
from .reasoner import Config, ReasonResult, reason


def sql_reason(spark: SparkSession, view: str = "triples", config: Config | None = None) -> ReasonResult:
    """Close the view's triples; leaves views ``closure``, ``schema_closure`` and ``rule_stats``."""
    result = reason(spark.table(view).select("s", "p", "o"), config)
    result.register(spark)
    return result


def register_functions(spark: SparkSession) -> None:
    """``html_links`` and ``expand_clique`` for LATERAL joins, ``parse_ntriple`` for expressions."""
    spark.udtf.register("html_links", HtmlLinks)
    spark.udtf.register("expand_clique", ExpandClique)
    spark.udf.register("parse_ntriple", parse_ntriple)
