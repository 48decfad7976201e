"""Secret scans: patterns, and character Markov models of random strings against ordinary identifiers.

Three patterns give the base findings (assignments, access keys, long hexadecimal runs).  Beside them, every
token of at least ``MIN_TOKEN`` characters is compared under two first-order character models, one trained on
random strings and one on identifiers; tokens whose log-likelihood ratio exceeds ``THRESHOLD`` and that overlap no
base finding are findings of kind ``random``.

All of it is SQL functions.  Matches are located by setting marks around them (marks in the text itself become
another private character first, which keeps lengths), cutting at the marks and adding up lengths.  Sums run in portions
(:func:`with_running`), and spans meet in one sorted list, so a text of very many matches costs little more than in proportion.

The identifiers of the labelled sample are words of about ``SAMPLE_DOCS`` documents, alone and joined in runs of ``JOINED``
in snake and camel case; the random strings are digests in several alphabets.  Training counts pairs of characters, so
what reaches the driver is bounded by the alphabet.

Edge cases: null is the empty text, without findings; offsets are code points, end exclusive; repeated rows are
scanned alike; an empty table gives an empty result (and a model from random strings alone); input columns of any
name stay as they are, since working columns lie in structs of their own.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MIN_TOKEN = 20
THRESHOLD = 12.0
SAMPLE_DOCS = 2000
RANDOM_STRINGS = 3000
#: Words that are joined to one identifier.
JOINED = 40
#: Elements that a running sum takes at a time.
PORTION = 128
PAGE = 4096
#: Hashes are drawn from so many that the share of a sample stays exact in any number of documents.
LOTS = 1 << 48
MASK = "<secret>"

#: Patterns and the group whose length is tested, with that length.  Fixed values.
KINDS = (
    ("assign", r"""(?i:(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+))""", 1, 8),
    ("access", r"AKIA[A-Z0-9]+", 0, 16),
    ("hex", r"[0-9a-f]+", 0, 32),
)
#: A run of hexadecimal digits fails by its length alone, so shorter runs need not be marked.
_SEARCH = {"hex": r"[0-9a-f]{32,}"}
TOKEN = rf"[A-Za-z0-9+/_-]{{{MIN_TOKEN},}}"
ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_-"

_FAR = (1 << 31) - 1
_OPEN, _CLOSE, _OTHER = "\ue000", "\ue001", "\ue002"


def _larger(a: F.Column, b: F.Column) -> F.Column:
    return F.greatest(a, b)


def with_running(rows: DataFrame, wanted: dict[str, str], best=None) -> DataFrame:
    """``rows`` with arrays of running sums (or of running bests); wanted: their names by those of arrays of whole numbers, none
    below zero.

    Appending to an array copies it, so one running pass would be quadratic; portions are summed alone and moved by what came
    before them.  Arrays must be columns: an expression inside a lambda would be computed again for each element.
    """
    best = best or (lambda a, b: a + b)
    start = F.array(F.lit(0))
    extend = lambda acc, x: F.concat(acc, F.array(best(F.element_at(acc, -1), x)))
    portions = {}
    for name in wanted:
        numbers = F.sequence(F.lit(0), F.floor((F.greatest(F.size(name), F.lit(1)) - 1) / PORTION).cast("int"))
        portions[f"{name}_portions"] = F.transform(numbers, (lambda name: lambda k: F.aggregate(F.slice(name, k * PORTION + 1, PORTION), start, extend))(name))
    moved = {}
    for name, out in wanted.items():
        inner = F.col(f"{name}_portions")
        before = F.aggregate(F.transform(inner, lambda p: F.element_at(p, -1)), start, extend)
        moved[out] = F.flatten(F.zip_with(inner, F.slice(before, 1, F.size(inner)), lambda p, b: F.transform(F.slice(p, 2, PORTION), lambda x: best(x, b))))
    return rows.withColumns(portions).withColumns(moved).drop(*portions)


MATCH = "array<struct<start:int,end:int,hit:string>>"


def with_matches(rows: DataFrame, patterns: dict[str, str]) -> DataFrame:
    """``rows`` (with a column ``text``) with arrays of (start, end, hit): the leftmost non-overlapping matches of patterns."""
    rows = rows.withColumn("clean", F.translate("text", _OPEN + _CLOSE, _OTHER + _OTHER))
    rows = rows.withColumns({f"{k}_pieces": F.split(F.regexp_replace("clean", f"({p})", f"{_OPEN}$1{_CLOSE}"), _OPEN) for k, p in patterns.items()})
    # Each piece after the first is a match and what follows it.
    rows = rows.withColumns({f"{k}_sizes": F.transform(f"{k}_pieces", lambda x: F.length(x) - F.when(F.instr(x, _CLOSE) > 0, 1).otherwise(0)) for k in patterns})
    rows = with_running(rows, {f"{k}_sizes": f"{k}_sums" for k in patterns})
    found = {}
    for k in patterns:
        n = F.size(f"{k}_pieces") - 1
        met = F.zip_with(F.slice(f"{k}_sums", 1, n), F.slice(f"{k}_pieces", 2, n), lambda at, x: F.struct(at.alias("start"), (at + F.instr(x, _CLOSE) - 1).alias("end"), F.substring_index(x, _CLOSE, 1).alias("hit")))
        found[k] = F.when(n > 0, met.cast(MATCH)).otherwise(F.array().cast(MATCH))
    return rows.withColumns(found).drop("clean", *[f"{k}_{x}" for k in patterns for x in ("pieces", "sizes", "sums")])


def shaped(found: F.Column, order: int, kind: str) -> F.Column:
    return F.transform(found, lambda m: F.struct(m["start"].alias("start"), F.lit(order).alias("order"), m["end"].alias("end"), F.lit(kind).alias("kind")))


def base_kind(order: int, kind: str, pattern: str, group: int, least: int) -> F.Column:
    """The spans of a base kind from the matches in the column of its name: those whose tested group is long enough."""
    size = (lambda m: F.length(F.regexp_extract(m["hit"], pattern, group))) if group else (lambda m: m["end"] - m["start"])
    return shaped(F.filter(kind, lambda m: size(m) >= least), order, kind)


def labelled(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """(s, random): the labelled sample."""
    n = max(1, docs.select("doc_id").count())
    lot = F.pmod(F.xxhash64(F.lit("secrets"), F.col("doc_id")), F.lit(LOTS))
    chosen = docs.where(lot < float(LOTS) * sample_docs / n).select(F.regexp_extract_all("text", F.lit(r"(?<![A-Za-z0-9+/_-])([A-Za-z]{3,})(?![A-Za-z0-9+/_-])")).alias("w"))
    words = chosen.select(F.explode(F.filter(F.array_distinct("w"), lambda x: F.length(x) < MIN_TOKEN)).alias("s"))
    # Words in runs, by turns in snake and in camel case.
    runs = chosen.where(F.size("w") > 0).select("w", F.explode(F.sequence(F.lit(0), F.floor((F.size("w") - 1) / JOINED).cast("int"))).alias("k"))
    run = F.slice("w", F.col("k") * JOINED + 1, JOINED)
    joined = runs.select(F.when(F.col("k") % 2 == 0, F.array_join(run, "_")).otherwise(F.array_join(F.transform(run, F.initcap), "")).alias("s"))
    digest = F.sha2(F.col("id").cast("string").cast("binary"), 256)
    strings = docs.sparkSession.range(RANDOM_STRINGS).select(
        F.explode(F.array(digest, F.upper(digest), F.base64(F.unhex(digest)), F.translate(F.base64(F.unhex(digest)), "+/=", "-_"), F.upper(F.translate(F.base64(F.unhex(digest)), "+/=", "")))).alias("s")
    )
    return words.select("s", F.lit(False).alias("random")).union(joined.select("s", F.lit(False))).union(strings.select("s", F.lit(True)))


def train(sample: DataFrame) -> list[float]:
    """Log-likelihood ratios of character pairs, row by row of the alphabet, add-one smoothed."""
    chars = F.filter(F.split("s", ""), lambda c: F.instr(F.lit(ALPHABET), c) > 0)
    pairs = sample.select("random", chars.alias("c")).select("random", F.explode(F.zip_with(F.col("c"), F.slice("c", 2, 1 << 30), lambda a, b: F.concat(a, b))).alias("pair"))
    count = {(r["random"], r["pair"]): r["n"] for r in pairs.where("length(pair) = 2").groupBy("random", "pair").agg(F.count("*").alias("n")).collect()}
    out = []
    for a in ALPHABET:
        total = [sum(count.get((kind, a + b), 0) for b in ALPHABET) for kind in (False, True)]
        for b in ALPHABET:
            p, q = ((count.get((kind, a + b), 0) + 1) / (total[kind] + len(ALPHABET)) for kind in (True, False))
            out.append(math.log(p / q))
    return out


def ratio(token: F.Column, table: list[float]) -> F.Column:
    """Log-likelihood ratio of one token, random over identifier."""
    numbers = F.split(F.lit(" ".join(f"{x:.6f}" for x in table)), " ").cast("array<double>")
    places = F.transform(F.split(token, ""), lambda c: F.instr(F.lit(ALPHABET), c) - 1)
    width = len(ALPHABET)
    start = F.struct(F.lit(-1).alias("last"), F.lit(0.0).alias("sum"))
    both = lambda acc, k: (acc["last"] >= 0) & (k >= 0)
    step = lambda acc, k: F.struct(k.alias("last"), (acc["sum"] + F.when(both(acc, k), F.get(numbers, acc["last"] * width + k)).otherwise(0.0)).alias("sum"))
    return F.aggregate(places, start, step, lambda acc: acc["sum"])


def scan(docs: DataFrame, table: list[float], threshold: float = THRESHOLD) -> DataFrame:
    """row (a struct of the columns of ``docs``) and found: a struct of ``n_<kind>`` for each base kind, and of ``base`` and ``spans``,
    sorted arrays of (start, order, end, kind)."""
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    rows = with_matches(rows, {kind: _SEARCH.get(kind, pattern) for kind, pattern, *_ in KINDS} | {"token": TOKEN}).drop("text")
    rows = rows.select("row", *[base_kind(k, *x).alias(x[0]) for k, x in enumerate(KINDS)], shaped(F.filter("token", lambda t: ratio(t["hit"], table) > threshold), len(KINDS), "random").alias("random"))
    rows = rows.withColumn("base", F.array_sort(F.concat(*[kind for kind, *_ in KINDS])))
    rows = rows.withColumn("every", F.array_sort(F.concat("base", "random")))
    # A random span goes where a base span before it ends inside or beyond, or one behind it begins inside.
    is_base = lambda s: s["order"] < len(KINDS)
    rows = rows.withColumns(
        {
            "ends": F.transform("every", lambda s: F.when(is_base(s), s["end"]).otherwise(0)),
            "begins": F.reverse(F.transform("every", lambda s: F.when(is_base(s), _FAR - s["start"]).otherwise(0))),
        }
    )
    rows = with_running(rows, {"ends": "reached", "begins": "ahead"}, _larger)
    judged = F.zip_with(
        F.zip_with("every", "reached", lambda s, e: F.struct(s.alias("s"), (is_base(s) | (e <= s["start"])).alias("free"))),
        F.reverse("ahead"),
        lambda x, a: F.struct(x["s"].alias("s"), (x["free"] & (is_base(x["s"]) | (_FAR - a >= x["s"]["end"]))).alias("free")),
    )
    spans = F.transform(F.filter(judged, lambda x: x["free"]), lambda x: x["s"])
    counts = [F.size(kind).cast("long").alias(f"n_{kind}") for kind, *_ in KINDS]
    return rows.select("row", F.struct(*counts, F.col("base"), F.when(F.size("random") > 0, spans).otherwise(F.col("base")).alias("spans")).alias("found"))


def listed(spans: F.Column) -> F.Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def report(docs: DataFrame) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans."""
    found = scan(docs.select("doc_id", "text"), train(labelled(docs)))
    counts = [f"found.n_{kind}" for kind, *_ in KINDS]
    return found.select("row.doc_id", *counts, F.sha2(listed(F.col("found.base")).cast("binary"), 256).alias("base_sha256"), listed(F.col("found.spans")).alias("spans"))


def _piece(pages: F.Column, a: F.Column, b: F.Column) -> F.Column:
    """Code points a to b of a text in pages."""
    first, last = F.floor(a / PAGE).cast("int"), F.floor(b / PAGE).cast("int")
    middle = F.array_join(F.slice(pages, first + 2, F.greatest(last - first - 1, F.lit(0))), "")
    apart = F.concat(F.substring(F.get(pages, first), a % PAGE + 1, F.lit(PAGE)), middle, F.substring(F.get(pages, last), F.lit(1), b % PAGE))
    return F.when(first == last, F.substring(F.get(pages, first), a % PAGE + 1, b - a)).otherwise(apart)


def redact(docs: DataFrame) -> DataFrame:
    """All documents, findings replaced by ``MASK`` (overlapping ones by one); ``n_chars`` follows where it exists.

    Null texts stay null; texts without findings and all other columns stay as they were.
    """
    found = scan(docs, train(labelled(docs)))
    found = found.select("row", F.col("row")["text"].alias("text"), F.col("found.spans").alias("spans"))
    found = with_running(found.withColumn("ends", F.transform("spans", lambda s: s["end"])), {"ends": "reach"}, _larger)
    # A span that begins before an earlier one ends belongs to it: the furthest end so far tells.
    earlier = F.concat(F.array(F.lit(0)), F.slice("reach", 1, F.greatest(F.size("reach") - 1, F.lit(0))))
    first = F.zip_with("spans", F.slice(earlier, 1, F.size("spans")), lambda s, e: F.struct(s["start"].alias("start"), e.alias("before")))
    # Finding a place in a text walks from its begin, so pieces are cut from pages.
    pages = F.transform(F.sequence(F.lit(0), F.floor(F.length("text") / PAGE).cast("int")), lambda k: F.substring(F.col("text"), k * PAGE + 1, F.lit(PAGE)))
    found = found.select("row", "text", "reach", F.filter(first, lambda s: s["start"] >= s["before"]).alias("cuts"), F.when(F.size("spans") > 0, pages).alias("pages"))
    starts = F.concat(F.transform("cuts", lambda s: s["start"]), F.array(F.length("text")))
    ends = F.concat(F.transform("cuts", lambda s: s["before"]), F.array(F.try_element_at("reach", F.lit(-1))))
    pieces = F.zip_with(ends, starts, lambda a, b: _piece(F.col("pages"), a, b))
    changed = F.size("cuts") > 0
    found = found.select("row", changed.alias("changed"), F.when(changed, F.array_join(pieces, MASK)).otherwise(F.col("text")).alias("new"))
    out = []
    for c in docs.columns:
        own = F.col("row")[c]
        if c == "text":
            own = F.col("new")
        elif c == "n_chars":
            own = F.when(F.col("changed"), F.length("new")).otherwise(own).cast(docs.schema[c].dataType)
        out.append(own.alias(c))
    return found.select(*out)
