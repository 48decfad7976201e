"""Firing one rule: its premises as joins.

Schema premises are small and are joined with each other first; the result, of checked size, is broadcast.  An instance
premise is narrowed by it on the map side before anything is shuffled, and two instance premises meet in one equi-join.  With
a delta a rule is evaluated semi-naively: each instance premise in turn reads the delta, the others everything known.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.rules import RULES, Atom, Rule
from ..triples import narrowed
from ..vocab import VOCAB, Vocabulary

#: Rows of joined schema premises that are broadcast; more are shuffled.
BROADCAST_ROWS = 1_000_000

Parts = dict[str, DataFrame]


@dataclass
class Schema:
    """Schema triples with the joined premises of each rule, counted once."""

    triples: DataFrame
    vocab: Vocabulary = VOCAB
    broadcast: bool = True
    #: The triples where the driver holds them anyway; premises are then joined there.
    rows: frozenset[tuple[str, str, str]] | None = None
    _joined: dict[str, tuple[DataFrame, int]] = field(default_factory=dict)
    _wanted: dict[str, list[tuple[str, set[str] | None]]] = field(default_factory=dict)
    _local: dict[str, tuple[list[str], set[tuple[str, ...]]] | None] = field(default_factory=dict)

    def bindings(self, rule: Rule) -> tuple[DataFrame, int] | None:
        """(one row per way to satisfy the schema premises, number of rows)."""
        atoms = [a for a in rule.body if a.kind(self.vocab) == "schema"]
        if not atoms:
            return None
        if rule.id not in self._joined and self.local(rule) is not None:
            names, found = self.local(rule)
            kind = ", ".join(f"{n} string" for n in names)
            self._joined[rule.id] = (self.triples.sparkSession.createDataFrame(sorted(found), kind), len(found))
        if rule.id not in self._joined:
            rows = reduce(lambda x, y: x.join(y, [c for c in x.columns if c in y.columns]), [matched(a, self.triples) for a in atoms]).distinct()
            found = rows.limit(BROADCAST_ROWS + 1).collect()
            small = len(found) <= BROADCAST_ROWS
            self._joined[rule.id] = (self.triples.sparkSession.createDataFrame(found, rows.schema) if small else rows, len(found))
        return self._joined[rule.id]

    def local(self, rule: Rule) -> tuple[list[str], set[tuple[str, ...]]] | None:
        """The bindings in memory; None where the driver does not hold the schema or there are too many."""
        if rule.id not in self._local:
            atoms = [a for a in rule.body if a.kind(self.vocab) == "schema"]
            self._local[rule.id] = joined_locally(atoms, self.rows, BROADCAST_ROWS) if self.rows is not None else None
        return self._local[rule.id]

    def wanted(self, rule: Rule) -> list[tuple[str, set[str] | None]]:
        """(kind, predicates or, of types, classes that it can match; None: any) for each instance premise."""
        if rule.id not in self._wanted:
            atoms = [a for a in rule.body if a.kind(self.vocab) != "schema"]
            found = self.local(rule) if len(atoms) < len(rule.body) else ([], {()})
            out = []
            for a in atoms:
                kind = a.kind(self.vocab)
                term = a.o if kind == "type" else a.p
                if found is None or term.startswith("?") and variable(term) not in found[0]:
                    out.append((kind, None))
                else:
                    out.append((kind, {r[found[0].index(variable(term))] for r in found[1]} if term.startswith("?") else {term}))
            self._wanted[rule.id] = out
        return self._wanted[rule.id]

    def reach(self, rule: Rule) -> tuple[set[str], set[str]] | None:
        """(predicates, classes) that the rule's consequences can have, classes where the predicate is that of types; None where
        the schema does not say."""
        head, v = rule.head, self.vocab
        found = self.local(rule) if any(a.kind(v) == "schema" for a in rule.body) else ([], {()})
        if found is None:
            return None
        names, rows = found
        values = lambda term: {term} if not term.startswith("?") else {r[names.index(variable(term))] for r in rows} if variable(term) in names else None
        predicates = values(head.p)
        if predicates is None:
            return None
        if v.type not in predicates:
            return predicates, set()
        classes = values(head.o)
        return None if classes is None else (predicates, classes)

    def side(self, rule: Rule, columns: list[str] | None = None) -> DataFrame:
        rows, n = self.bindings(rule)
        rows = rows if columns is None else rows.select(*columns).distinct()
        return F.broadcast(rows) if self.broadcast and n <= BROADCAST_ROWS else rows


def joined_locally(atoms: list[Atom], rows, limit: int | None = None) -> tuple[list[str], set[tuple[str, ...]]] | None:
    """(column names, rows) of the conjunction of atoms over triples in memory, by hash joins; None beyond ``limit`` rows, which are
    counted before they are made."""
    names: list[str] = []
    found: list[tuple[str, ...]] = [()]
    for a in atoms:
        own = [variable(t) for t in a.variables()]
        shared = [n for n in own if n in names]
        index: dict[tuple[str, ...], list[tuple[str, ...]]] = {}
        for t in rows:
            bound: dict[str, str] = {}
            if all(bound.setdefault(variable(x), y) == y if x.startswith("?") else x == y for x, y in zip(a.terms(), t, strict=True)):
                index.setdefault(tuple(bound[n] for n in shared), []).append(tuple(bound[n] for n in own if n not in shared))
        at = [names.index(n) for n in shared]
        if limit is not None and sum(len(index.get(tuple(f[k] for k in at), ())) for f in found) > limit:
            return None
        found = [(*f, *more) for f in found for more in index.get(tuple(f[k] for k in at), ())]
        names += [n for n in own if n not in shared]
    return names, set(found)


def variable(term: str) -> str:
    return f"v_{term[1:]}"


def matched(atom: Atom, triples: DataFrame) -> DataFrame:
    """One column per variable for the triples that an atom matches."""
    where: list[Column] = []
    place: dict[str, str] = {}
    for column, term in zip("spo", atom.terms(), strict=True):
        if not term.startswith("?"):
            where.append(F.col(column) == term)
        elif term in place:
            where.append(F.col(column) == F.col(place[term]))
        else:
            place[term] = column
    for w in where:
        triples = triples.where(w)
    return triples.select(*[F.col(c).alias(variable(t)) for t, c in place.items()])


def _consequences(rows: DataFrame, rule: Rule, keep_reflexive: bool) -> DataFrame:
    if rule.differ and not keep_reflexive:
        rows = rows.where(F.col(variable(rule.differ[0])) != F.col(variable(rule.differ[1])))
    return rows.select(*[F.col(variable(t)).alias(c) if t.startswith("?") else F.lit(t).alias(c) for c, t in zip("spo", rule.head.terms(), strict=True)])


def fire(
    rule: Rule | str,
    schema: Schema,
    known: Parts,
    delta: Parts | None = None,
    keep_reflexive: bool = False,
    literal: Column | None = None,
) -> DataFrame | None:
    """What the rule derives, repeats included; None where a premise can't be met by the schema.

    known, delta: instance triples by kind (type, identity, fact).  literal: a condition on ``s`` that marks literals, which are
    kept from becoming subjects.
    """
    rule = RULES[rule] if isinstance(rule, str) else rule
    vocab = schema.vocab
    bound = schema.bindings(rule)
    if bound is not None and bound[1] == 0:
        return None
    atoms = [a for a in rule.body if a.kind(vocab) != "schema"]
    if not atoms:
        return _finish(_consequences(schema.side(rule), rule, keep_reflexive), literal)
    if rule.id == "O10":
        return _finish(substitute(known, delta), literal)
    out = []
    wanted = schema.wanted(rule)
    for turn in range(len(atoms)) if delta is not None else [None]:
        parts = []
        for k, a in enumerate(atoms):
            source = (delta if k == turn else known).get(a.kind(vocab))
            if source is None:
                break
            rows = matched(a, narrowed(source, wanted[k][1], "o" if wanted[k][0] == "type" else "p"))
            if bound is not None:
                shared = [c for c in bound[0].columns if c in rows.columns]
                if not parts:
                    rows = rows.join(schema.side(rule), shared)
                elif shared:
                    rows = rows.join(schema.side(rule, shared), shared, "left_semi")
            parts.append(rows)
        else:
            # Two instance premises meet on all they share, restriction class included.
            rows = reduce(lambda x, y: x.join(y, [c for c in x.columns if c in y.columns]), parts)
            out.append(_consequences(rows, rule, keep_reflexive))
    return _finish(reduce(DataFrame.union, out), literal) if out else None


def _finish(rows: DataFrame | None, literal: Column | None) -> DataFrame | None:
    return rows if rows is None or literal is None else rows.where(~literal)


def substitute(known: Parts, delta: Parts | None = None) -> DataFrame | None:
    """Facts and types with subject, object or both replaced by identical terms (each term counts as identical to itself).  Schema
    triples are left to the merging rules, identity triples to symmetry and transitivity."""

    def said(parts: Parts) -> DataFrame | None:
        found = [parts[k].select("s", "p", "o") for k in ("fact", "type") if parts.get(k) is not None]
        return reduce(DataFrame.union, found) if found else None

    rows, same = said(known), known.get("identity")
    if delta is None:
        return None if rows is None or same is None else _replaced(rows, same, same)
    out = []
    if said(delta) is not None and same is not None:
        out.append(_replaced(said(delta), same, same))
    if delta.get("identity") is not None and rows is not None:
        new = delta["identity"]
        out += [_replaced(rows, new, same), _replaced(rows, same, new)]
    return reduce(DataFrame.union, out) if out else None


def _replaced(facts: DataFrame, for_s: DataFrame, for_o: DataFrame) -> DataFrame:
    a, b = for_s.select(F.col("s").alias("i_s"), F.col("o").alias("x")), for_o.select(F.col("s").alias("i_o"), F.col("o").alias("y"))
    left = facts.join(a, F.col("s") == F.col("i_s")).select(F.col("x").alias("s"), "p", "o")
    right = facts.join(b, F.col("o") == F.col("i_o")).select("s", "p", F.col("y").alias("o"))
    both = left.join(b, F.col("o") == F.col("i_o")).select("s", "p", F.col("y").alias("o"))
    return left.union(right).union(both)


def fused_inverse(schema: Schema, facts: DataFrame) -> DataFrame | None:
    """Both directions of declared inverses in one pass over the facts."""
    pairs = schema.bindings(RULES["O7a"])
    if pairs[1] == 0:
        return None
    p, q = variable("?p"), variable("?q")
    rows = schema.side(RULES["O7a"])
    turned = rows.select(F.col(p).alias("p"), F.col(q).alias("q")).union(rows.select(F.col(q), F.col(p))).distinct()
    turned = F.broadcast(turned) if schema.broadcast and pairs[1] <= BROADCAST_ROWS else turned
    return facts.join(turned, "p").select(F.col("o").alias("s"), F.col("q").alias("p"), F.col("s").alias("o"))


def property_rewrites(schema_rows: list[tuple[str, str, str]], vocab: Vocabulary = VOCAB) -> set[tuple[str, str, bool]]:
    """(p, q, swap): what R3, O3 and O7 together make of a fact's predicate, closed on the driver.

    These rules only rename the predicate and may turn the ends, so their joint closure depends on the schema alone.
    """
    step: dict[str, set[tuple[str, bool]]] = {}
    for s, p, o in schema_rows:
        if p == vocab.sub_property:
            step.setdefault(s, set()).add((o, False))
        elif p == vocab.inverse:
            step.setdefault(s, set()).add((o, True))
            step.setdefault(o, set()).add((s, True))
        elif p == vocab.type and o == vocab.symmetric:
            step.setdefault(s, set()).add((s, True))
    out = set()
    for start in step:
        seen, stack = set(), [(start, False)]
        while stack:
            q, swap = stack.pop()
            for r, turn in step.get(q, ()):
                if (x := (r, swap != turn)) not in seen:
                    seen.add(x)
                    stack.append(x)
        out |= {(start, q, swap) for q, swap in seen if (q, swap) != (start, False)}
    return out


def fused_facts(facts: DataFrame, rewrites: DataFrame, n: int | None = None) -> DataFrame:
    """R3, O3 and O7 to their joint fixpoint in one join; ``rewrites``: p, q, swap, broadcast where there are at most ``BROADCAST_ROWS``
    (``n``, counted if not given)."""
    n = rewrites.limit(BROADCAST_ROWS + 1).count() if n is None else n
    met = facts.join(F.broadcast(rewrites) if n <= BROADCAST_ROWS else rewrites, "p")
    return met.select(F.when(F.col("swap"), F.col("o")).otherwise(F.col("s")).alias("s"), F.col("q").alias("p"), F.when(F.col("swap"), F.col("s")).otherwise(F.col("o")).alias("o"))
