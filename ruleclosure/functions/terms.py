"""Functions on terms.  Columns stay in generated code; Python functions are there for what SQL can't say."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..shipping import by_value

by_value(__name__)

TRIPLE_STRUCT = T.StructType([T.StructField(c, T.StringType()) for c in ("s", "p", "o")])


def term(kind: str, key: Column) -> Column:
    return F.concat(F.lit(f"{kind}/"), key.cast("string"))


def local_name(iri: Column) -> Column:
    """What follows the last ``/``, ``#`` or ``:``."""
    return F.regexp_extract(iri, "([^/#:]*)$", 1)


def namespace(iri: Column) -> Column:
    return F.regexp_extract(iri, "^(.*[/#:])[^/#:]*$", 1)


_LINE = re.compile(r'^\s*<([^>]*)>\s*<([^>]*)>\s*(?:<([^>]*)>|"((?:[^"\\]|\\.)*)"(?:\^\^<[^>]*>|@[A-Za-z-]+)?)\s*\.\s*$')
_ESCAPES = {"\\t": "\t", "\\n": "\n", "\\r": "\r", '\\"': '"', "\\\\": "\\"}


def unescape(text: str) -> str:
    text = re.sub(r'\\[tnr"\\]', lambda m: _ESCAPES[m[0]], text)
    return re.sub(r"\\u([0-9A-Fa-f]{4})|\\U([0-9A-Fa-f]{8})", lambda m: chr(int(m[1] or m[2], 16)), text)


def escape(column: Column) -> Column:
    for plain, coded in (("\\", "\\\\"), ('"', '\\"'), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t")):
        column = F.replace(column, F.lit(plain), F.lit(coded))
    return column


def parse_line(line: str | None) -> tuple[str | None, str | None, str | None]:
    m = _LINE.match(line or "")
    return (m[1], m[2], m[3] if m[3] is not None else unescape(m[4])) if m else (None, None, None)


@F.pandas_udf(TRIPLE_STRUCT)
def parse_ntriple(lines: pd.Series) -> pd.DataFrame:
    """One N-Triples line each; lines that are none give nulls."""
    return pd.DataFrame([parse_line(x) for x in lines], columns=["s", "p", "o"])


@F.pandas_udf(T.StringType())
def clique_rep(terms: pd.Series) -> str:
    """The smallest term of a group (the built-in ``min`` does the same within generated code)."""
    return terms.min()


@F.udtf(returnType=T.StructType([T.StructField("href", T.StringType())]))
class HtmlLinks:
    """The targets of the links of a page."""

    def eval(self, html: str):
        for x in re.findall(r'href="([^"]*)"', html or ""):
            yield (x,)


@F.udtf(returnType=T.StructType([T.StructField("v", T.StringType()), T.StructField("w", T.StringType())]))
class ExpandClique:
    """All ordered pairs of different members."""

    def eval(self, members):
        for a in members or []:
            for b in members:
                if a != b:
                    yield a, b
