"""Transitive closure of keyed edges (p, src, dst), in several ways.

``doubling`` composes the frontier with itself, so rounds grow with the logarithm of the longest shortest path; ``linear``
joins the last delta with the edges, one step a round; ``naive`` joins everything with everything; ``sql`` is Spark's
recursive query (acyclic, few levels; deeper relations are finished by doubling); ``grouped`` closes each group of an acyclic forest in one worker; ``local``
closes a relation of checked size on the driver.  All give the same pairs.

A closed relation that gains edges is closed again from the new ones alone (:func:`extend_relation`).

Every round is cut into the shared folder, so a lost executor costs one round, and the plan does not grow.  With
``partitions`` all sides of a round are dealt by property and the node they meet in before the first round, so that
edges and frontier move once a round.

Many edges are closed over numbers in place of terms, given out once and exact; only the result is read back into terms.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..durable import Stored, cut, store
from ..shipping import by_value

by_value(__name__)

LOCAL_ROWS = 100_000
#: Edges that are broadcast to a closed relation; more meet it in a join.
FEW_ROWS = 200_000
#: Edges beyond which a closure's rounds run over numbers.
MANY_EDGES = 200_000
EDGE = "p string, src string, dst string"


def _compose(a: DataFrame, b: DataFrame) -> DataFrame:
    left = a.select("p", "src", F.col("dst").alias("via"))
    right = b.select("p", F.col("src").alias("via"), "dst")
    # The node first: it tells rows apart where a sort compares, which few properties don't.
    return left.join(right, ["via", "p"]).select("p", "src", "dst")


def _dealt(rows: DataFrame, partitions: int | None, node: str) -> DataFrame:
    """``rows`` dealt by property and ``node``, as the joins of a round want them; the checkpoint keeps that partitioning."""
    return rows if partitions is None else rows.repartition(partitions, "p", node)


def _less(a: DataFrame, known: DataFrame) -> DataFrame:
    return a.join(known, ["p", "src", "dst"], "left_anti")


class Limit(RuntimeError):
    """A closure outgrew what its caller allows."""


def close_relation(edges: DataFrame, method: str = "doubling", max_rounds: int = 200, max_rows: int | None = None, group: str | None = None, partitions: int | None = None, kept: list[Stored] | None = None, beyond: bool = False) -> DataFrame:
    """All pairs connected by at least one edge of the same ``p``.  kept: takes what the returned relation reads, where it is in files.
    beyond: without the edges themselves."""
    if beyond and method not in ("doubling", "linear", "naive"):
        return _less(close_relation(edges, method, max_rounds, max_rows, group, partitions, kept), edges)
    edges = edges.select("p", "src", "dst").distinct()
    if method == "local":
        return close_locally(edges)
    if method == "sql":
        return close_in_sql(edges)
    if method == "grouped":
        return close_groups(edges, group)
    # Edges are looked up by their source in every linear round.
    edges = _stored(_dealt(edges, partitions, "src"), partitions)
    terms = None
    if partitions is None and edges.rows > MANY_EDGES:
        terms = _numbers(edges.frame)
        named, edges = edges, store(_over(edges.frame, terms.frame, "term", "number"))
        named.forget()
    known, delta, rounds = edges, edges, 0
    while True:
        rounds += 1
        if rounds > max_rounds:
            raise Limit(f"no fixpoint in {max_rounds} rounds")
        at, all_ = delta.frame, known.frame
        if method == "doubling":
            new = _stored(_dealt(_less(_compose(_dealt(at, partitions, "dst"), at).distinct(), all_), partitions, "src"), partitions)
        elif method == "linear":
            new = _stored(_less(_compose(_dealt(at, partitions, "dst"), edges.frame).distinct(), all_), partitions)
        elif method == "naive":
            new = _stored(_less(_compose(all_, all_).distinct(), all_), partitions)
        else:
            raise ValueError(method)
        if new.rows == 0:
            _forget([edges, delta, new], [known, *([edges] if beyond else [])])
            if kept is not None:
                read = {x.folder: x for x in (known, terms, edges if beyond else known) if x is not None and x.folder}
                kept.extend(read.values())
            found = _less(all_, edges.frame) if beyond else all_
            return found if terms is None else _over(found, terms.frame, "number", "term")
        # Pairs between this distance and the next, when doubling: a known pair, then a new one.
        grown = all_.union(new.frame).union(_compose(all_, new.frame)).distinct() if method == "doubling" else all_.union(new.frame)
        grown = _stored(grown, partitions)
        _forget([known, delta], [new, *([edges] if method == "linear" or beyond else [])])
        known, delta = grown, new
        if max_rows is not None and known.rows > max_rows:
            raise Limit(f"the closure has more than {max_rows} rows")


def _numbers(edges: DataFrame) -> Stored:
    """term, number: a number for each node of the edges, fixed by writing it."""
    terms = edges.select(F.explode(F.array("src", "dst")).alias("term")).where("term IS NOT NULL").distinct()
    return store(terms.select("term", F.monotonically_increasing_id().alias("number")))


def _over(rows: DataFrame, terms: DataFrame, have: str, want: str) -> DataFrame:
    """Rows with ``want`` of each node in place of what they ``have``; what is null stays null."""
    for c in ("dst", "src"):
        rows = rows.join(terms.select(F.col(have).alias(c), F.col(want).alias("put")), c, "left").drop(c).withColumnRenamed("put", c)
    return rows.select("p", "src", "dst")


def _stored(rows: DataFrame, partitions: int | None) -> Stored:
    """A round's rows in files; as a checkpoint, without a folder to forget, where their partitioning is to stay."""
    if partitions is None:
        return store(rows)
    rows = cut(rows)
    return Stored(rows, "", rows.count())


def _forget(old: list[Stored], still: list[Stored]) -> None:
    for folder, x in {x.folder: x for x in old}.items():
        if folder and folder not in {y.folder for y in still}:
            x.forget()


def extend_relation(closed: DataFrame, edges: DataFrame, max_rounds: int = 200) -> tuple[DataFrame, DataFrame, int]:
    """(the closure of ``closed``, which is closed, with ``edges``; what it gained; number of edges that were new)."""
    found = extension(closed, edges, max_rounds)
    if found is None:
        return closed, closed.limit(0), 0
    delta, rest, files = found
    gained = delta.frame.union(cut(rest))
    _forget(files, [])
    return closed.union(gained), gained, delta.rows


def extension(closed: DataFrame, edges: DataFrame, max_rounds: int = 200) -> tuple[Stored, DataFrame, list[Stored]] | None:
    """(edges that a closed relation does not have; the other pairs that it gains with them; files that these are made from),
    None where no edge is new.

    A path over a new edge is a known pair or none, then links: each a new edge, with a known pair behind it or none.
    The links are closed by themselves, and what was known meets their closure once.
    """
    asked = store(edges.select("p", "src", "dst").distinct())
    few = asked.rows <= FEW_ROWS
    again = closed.join(F.broadcast(asked.frame), ["p", "src", "dst"], "left_semi") if few else closed
    delta = store(asked.frame.join(F.broadcast(again) if few else again, ["p", "src", "dst"], "left_anti"))
    asked.forget()
    if delta.rows == 0:
        delta.forget()
        return None
    files: list[Stored] = []
    links = close_relation(delta.frame.union(_compose(delta.frame, closed)), max_rounds=max_rounds, kept=files)
    # Of what is known, a path can only repeat pairs that end where links end.
    ends = closed.join(links.select("p", "dst").distinct(), ["p", "dst"], "left_semi").select("p", "src", "dst")
    return delta, _less(links.union(_compose(closed, links)).distinct(), ends.union(delta.frame)), files


def closed_pairs(pairs: Iterable[tuple[str, str, str]]) -> set[tuple[str, str, str]]:
    """The closure of (p, src, dst) rows in memory."""
    follow: dict[tuple[str, str], set[str]] = defaultdict(set)
    for p, a, b in pairs:
        follow[p, a].add(b)
    out = set()
    for p, a in list(follow):
        seen, stack = set(), list(follow[p, a])
        while stack:
            b = stack.pop()
            if b not in seen:
                seen.add(b)
                stack += follow.get((p, b), ())
        out |= {(p, a, b) for b in seen}
    return out


def close_locally(edges: DataFrame, limit: int = LOCAL_ROWS) -> DataFrame:
    """On the driver; a relation of more than ``limit`` edges is closed by doubling instead."""
    rows = edges.limit(limit + 1).collect()
    if len(rows) > limit:
        return close_relation(edges, "doubling")
    return edges.sparkSession.createDataFrame(sorted(closed_pairs(map(tuple, rows))), EDGE)


def close_in_sql(edges: DataFrame, depth: int = 99) -> DataFrame:
    """A recursive query.  Spark unions without removing repeats and stops at 100 levels, so it suits acyclic edges of few paths.

    Where the last level can still be extended, the relation is closed by doubling instead, so no pair is lost.
    """
    edges = cut(edges)
    reach = cut(
        edges.sparkSession.sql(
            f"""
        WITH RECURSIVE reach(p, src, dst, n) AS (
            SELECT p, src, dst, 1 FROM {{edges}}
            UNION ALL
            SELECT r.p, r.src, e.dst, r.n + 1 FROM reach r JOIN {{edges}} e ON r.p = e.p AND r.dst = e.src WHERE r.n < {depth}
        )
        SELECT p, src, dst, n FROM reach""",
            edges=edges,
        )
    )
    if not _compose(reach.where(F.col("n") == depth), edges).isEmpty():
        return close_relation(edges, "doubling")
    return reach.select("p", "src", "dst").distinct()


def close_groups(edges: DataFrame, group: str | None) -> DataFrame:
    """Each group of ``group`` (an SQL expression over p and src that no path leaves) in one worker, one shuffle in all.

    For relations that fall into many small components; a group must fit a worker.
    """

    def close(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame(sorted(closed_pairs(pdf[["p", "src", "dst"]].itertuples(index=False, name=None))), columns=["p", "src", "dst"])

    keyed = edges.withColumn("g", F.expr(group or "p"))
    return keyed.groupBy("p", "g").applyInPandas(close, EDGE)
