"""The ordered closure: schema once, fact and type stages in turn to a fixpoint, then identity.

A stage runs its rules in order over what is known, later rules seeing what earlier ones derived in the same pass, and
ends with one removal of repeats and of known triples, cut into the shared folder.  Rules that drop a term of what they read lose their
repeats at once, as later rules of the pass would multiply them (not with ``count_raw``).  The loop ends when neither stage found anything.

The input and the results of stages lie in files by name (predicate, or class of types), so that a rule's scan reads little but what
it can match.

What is known does not move without need: the schema says which predicates and classes a stage's rules can derive, and only
known triples of these meet its results, in one aggregation; where results are few, they are broadcast to the known ones instead.
With ``delta`` (the default) rules read only what is new since the stage last ran, and a rule that gains nothing from its own
results does not read them; transitive properties stay closed and are extended from new edges alone.  The driver knows which
predicates and classes the new triples have (as long as these are few), so rules that can't match any of them cost no job.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .durable import Stored, cut, store
from .operators.closure import close_relation, closed_pairs, extension
from .operators.firing import Schema, fire, fused_facts, property_rewrites
from .operators.identity import canonicalize, pair_closure, rewrite, star_pairs
from .plans.orders import Plan, compose_plan
from .plans.rules import MERGING, RULES, Rule
from .triples import MAX_NAMES, TRIPLE, classify, narrowed, placed
from .vocab import VOCAB, Vocabulary

#: Schema triples that the driver closes in memory; a larger schema is an error that names this bound.
MAX_SCHEMA = 1_000_000
#: Results of a stage that are broadcast to what is known; more meet it in an aggregation.
FEW_RESULTS = 200_000
#: Files of a result that an incremental closure shares; those of more are written anew as one.
MANY_FILES = 60
#: What is new, by kind: (predicate or, of types, class; rule it comes from), or None where there are too many.
Names = dict[str, set[tuple[str, str]] | None]
#: Rules that gain nothing from their own results, and the schema rule without which that does not hold.
ONCE = {"R3": "R2", "R6": "R1", "O3": None, "O4": None, "R3+O3+O7": "R2"}
#: Rules that give a fact another predicate, and may turn it: (property, consequence) among their variables.
RENAMES = {"R3": ("v_p", "v_q"), "O3": ("v_p", "v_p"), "O7a": ("v_p", "v_q"), "O7b": ("v_q", "v_p")}
#: Rules that drop a term of an instance premise, so that many matches give one triple.
REPEATING = ("R4", "R5", "O15", "O16")
#: Columns of known triples: the last is the bucket that their files are dealt by.
KNOWN = ("s", "p", "o", "b")
STATS = "round int, stage string, rule string, raw long, fresh long, secs double"


@dataclass(frozen=True)
class Config:
    plan: Plan = field(default_factory=compose_plan)
    rules: tuple[str, ...] | None = None
    #: final: identity once, last (not the closure of all rules); fixpoint: repeat all stages; canonical: one
    #: representative for each clique, facts rewritten; off.
    identity_mode: str = "final"
    include_merging_rules: bool = False
    broadcast: bool = True
    delta: bool = True
    fused: bool = False
    closure_method: str = "doubling"
    #: Deal both sides of a closure's joins into so many partitions once, and keep them.
    closure_partitions: int | None = None
    keep_reflexive: bool = False
    vocab: Vocabulary = VOCAB
    rule_set: dict[str, Rule] = field(default_factory=lambda: RULES)
    max_rounds: int = 50
    provenance: bool = False
    #: Also report derivations before repeats go.
    count_raw: bool = False

    @staticmethod
    def from_shares(shares: dict[str, float], **options) -> Config:
        """Effort by class size: identity is skipped where no rule can make any, and kept as representatives where cliques
        may be large."""
        share = shares.get("identity", 0.0)
        return Config(identity_mode="off" if share == 0 else "final" if share < 1 else "canonical", **options)

    def uses(self, rule: str) -> bool:
        if rule in MERGING and not self.include_merging_rules:
            return False
        return self.rules is None or rule in self.rules


@dataclass
class ReasonResult:
    closure: DataFrame
    derived: DataFrame
    schema: DataFrame
    rounds: int
    stats: list[tuple]
    reps: DataFrame | None = None
    #: What its frames read.
    stored: list[Stored] = field(default_factory=list)
    #: What an incremental closure goes on from.
    run: Run | None = None

    def forget(self) -> None:
        """Remove the files behind the frames, which can't be read from then on."""
        while self.stored:
            self.stored.pop().forget()

    def stats_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.stats, STATS)

    def register(self, spark: SparkSession) -> None:
        """Views ``closure``, ``schema_closure`` and ``rule_stats``."""
        self.closure.createOrReplaceTempView("closure")
        self.schema.createOrReplaceTempView("schema_closure")
        self.stats_df(spark).createOrReplaceTempView("rule_stats")


def close_schema(rows: set[tuple[str, str, str]], config: Config) -> set[tuple[str, str, str]]:
    """The schema stage on the driver, rules in the plan's order."""
    v, known = config.vocab, set(rows)
    by = lambda p: {(s, o) for s, q, o in known if q == p}
    edges = {"R1": v.sub_class, "R2": v.sub_property}
    same = {"O11": (v.equivalent_class, v.sub_class), "O12": (v.equivalent_property, v.sub_property)}
    for rule in config.plan.schema.rules:
        if not config.uses(rule):
            continue
        if rule in edges:
            p = edges[rule]
            new = {(a, q, b) for q, a, b in closed_pairs((p, a, b) for a, b in by(p))}
        else:
            equivalent, sub = same[rule[:-1]]
            if rule[-1] == "c":
                pairs = by(sub)
                new = {(a, equivalent, b) for a, b in pairs if (b, a) in pairs}
            else:
                new = {(a, sub, b) if rule[-1] == "a" else (b, sub, a) for a, b in by(equivalent)}
        known |= new if config.keep_reflexive else {t for t in new if t[0] != t[2]}
    return known


def schema_rows(triples: DataFrame) -> set[tuple[str, str, str]]:
    found = triples.limit(MAX_SCHEMA + 1).collect()
    if len(found) > MAX_SCHEMA:
        raise ValueError(f"more than {MAX_SCHEMA} schema triples")
    return {tuple(r) for r in found}


def _both(a: set[tuple[str, str]] | None, b: set[tuple[str, str]] | None) -> set[tuple[str, str]] | None:
    return None if a is None or b is None or len(a) + len(b) > 2 * MAX_NAMES else a | b


class Run:
    """One closure in the making."""

    def __init__(self, triples: DataFrame, config: Config):
        self.spark, self.config, v = triples.sparkSession, config, config.vocab
        self.stored = [store(placed(classify(triples.select("s", "p", "o").distinct(), v), v), "b")]
        #: Whether results are dealt into files by name, as the input is.
        self.large = self.stored[0].rows > FEW_RESULTS
        split = self.stored[0].frame
        self.input = split.select(*KNOWN)
        self.asserted = schema_rows(split.where("kind = 'schema'").select("s", "p", "o"))
        self.schema_set = close_schema(self.asserted, config)
        self.schema = self._schema()
        self.known = {k: split.where(F.col("kind") == k).select(*KNOWN) for k in ("type", "identity", "fact")}
        self.names: Names = self._names(split.where("kind <> 'schema'"))
        self.present = {k for k in self.known if self.names[k]} if None not in self.names.values() else {k for k in self.known if not self.known[k].isEmpty()}
        self.derived: list[DataFrame] = []
        self.stats: list[tuple] = []
        #: The closed pairs of transitive properties, once there are any, and how many new edges each closing took.
        self.closed: DataFrame | None = None
        self.closings: list[int] = []

    @classmethod
    def after(cls, before: Run, known: dict[str, DataFrame], names: Names, config: Config) -> Run:
        """A run that goes on from what another one knows, whose files it shares."""
        run = cls.__new__(cls)
        run.spark, run.config, run.stored, run.large = before.spark, config, list(before.stored), before.large
        run.asserted = before.schema_set
        run.schema_set = close_schema(run.asserted, config)
        run.schema = run._schema()
        run.known, run.names, run.present = known, names, set(known)
        run.derived, run.stats, run.closed, run.closings = [], [], None, []
        return run

    def arrived(self, new: dict[str, DataFrame], names: Names) -> None:
        """Triples with ``by``, none of them known, become known."""
        for k, x in new.items():
            plain = x.select(*KNOWN)
            self.known[k] = self.known[k].union(plain) if k in self.present else plain
            self.present.add(k)
            self.names[k] = _both(self.names.get(k, set()), names[k])

    def _schema(self) -> Schema:
        rows = self.spark.createDataFrame(sorted(self.schema_set), TRIPLE)
        return Schema(rows, self.config.vocab, self.config.broadcast, frozenset(self.schema_set))

    def _parts(self, parts: dict[str, list[DataFrame]]) -> dict[str, DataFrame]:
        return {k: reduce(DataFrame.union, x) for k, x in parts.items() if x}

    def _name(self) -> F.Column:
        return F.when(F.col("kind") == "type", F.col("o")).otherwise(F.col("p"))

    def _names(self, split: DataFrame) -> Names:
        """The names of triples with their kind."""
        found = split.select("kind", self._name().alias("name")).distinct().limit(MAX_NAMES + 1).collect()
        out: Names = {k: set() if len(found) <= MAX_NAMES else None for k in ("type", "identity", "fact")}
        for r in found if len(found) <= MAX_NAMES else ():
            out[r["kind"]].add((r["name"], ""))
        return out

    def _touched(self, rule: str, names: Names, seen: frozenset[str] = frozenset()) -> bool:
        """Whether a rule can match something new that does not come from a rule in ``seen``."""
        for one in ("R3", "O3", "O7a", "O7b") if rule == "R3+O3+O7" else (rule,):
            for kind, wanted in self.schema.wanted(self.config.rule_set[one]):
                have = names.get(kind, set())
                if have is None or any((wanted is None or x in wanted) and by not in seen and not (by == rule and self._once(rule)) for x, by in have):
                    return True
        return False

    def _once(self, rule: str) -> bool:
        needs = ONCE.get(rule, "")
        return needs is None or bool(needs) and self.config.uses(needs)

    def everything(self) -> dict[str, DataFrame]:
        """All known triples as something new."""
        return {k: self.known[k].withColumn("by", F.lit("")) for k in self.present}

    def _unread(self, rule: str, delta: dict[str, DataFrame], new: dict[str, list[DataFrame]], seen: frozenset[str]) -> dict[str, DataFrame]:
        """What a rule has to read of the new triples (with ``by``, the rule they come from): of those of the pass before, none that rules in
        ``seen`` derived, and all that this pass found so far."""
        past = seen | {rule} if self._once(rule) else seen
        parts = {k: [x.where(~F.col("by").isin(*sorted(past))) if past else x] for k, x in delta.items()}
        for k, x in new.items():
            parts.setdefault(k, []).extend(x)
        return self._parts(parts)

    def _running(self, rules: tuple[str, ...]) -> list[str]:
        """The stage's rules as they run, those that are fused as one."""
        todo, rename = [r for r in rules if self.config.uses(r)], ("R3", "O3", "O7a", "O7b")
        if not self.config.fused or not set(rename) & set(todo):
            return todo
        first = next(r for r in todo if r in rename)
        return ["R3+O3+O7" if r == first else r for r in todo if r == first or r not in rename]

    def stage(self, name: str, rules: tuple[str, ...], delta: dict[str, DataFrame] | None, number: int, names: Names | None = None, whole: bool = False) -> dict[str, DataFrame]:
        """Run one stage; returns what is new, by kind, with ``by``, and leaves its names in ``found_names``.  names: those of delta.
        whole: delta is all that is known, so a rule of two instance premises needs one join and not one for each."""
        config, began = self.config, time.time()
        names, self.found_names = names and {k: x and set(x) for k, x in names.items()}, {}
        made: Names = {}
        known = {k: [self.known[k]] for k in self.known if k in self.present}
        # What the pass derived, by kind, with its names; None where the schema does not say them.
        passed: dict[str, list[tuple[set[str] | None, DataFrame]]] = {}
        outs: list[tuple[str, Stored]] = []
        todo = self._running(rules)
        for at, rule in enumerate(todo):
            # In its last pass it read what the rules before it found.
            seen = frozenset(todo[:at])
            if delta is not None and names is not None and not self._touched(rule, names, seen) and not self._touched(rule, made):
                continue
            read = {k: [x for names_, x in rows if self._reads(rule, k, names_)] for k, rows in passed.items()}
            full = {k: known.get(k, []) + [x.select(*KNOWN) for x in read.get(k, [])] for k in {*known, *read}}
            unread = self._unread(rule, delta, read, seen) if delta is not None and not whole else None
            files: list[Stored] = []
            if rule == "R3+O3+O7":
                rows = self._fused((self._parts(full) if unread is None else unread).get("fact"))
            elif rule == "O4":
                rows = self._transitive(self._parts(full), unread, files)
            elif rule == "O6":
                rows = self._pairs(self._parts(full))
            else:
                rows = fire(config.rule_set[rule], self.schema, self._parts(full), unread, config.keep_reflexive)
            if rows is None:
                continue
            # Later rules of the pass read this one's rows, not its premises over again.  A cached plan would hold those of all
            # rules before it, which the driver prints with every job; files hold none, and go when the stage has settled.
            rows = rows.select("s", "p", "o")
            if rule in REPEATING and not config.count_raw:
                rows = rows.distinct()
            kept = store(placed(rows, config.vocab))
            for x in files:
                x.forget()
            if kept.rows == 0:
                kept.forget()
                continue
            rows = kept.frame
            outs.append((rule, kept))
            kind = {"R3+O3+O7": "fact"}.get(rule) or config.rule_set[rule].head.kind(config.vocab)
            for k, part in {"fact": rows.where(F.col("p") != config.vocab.type), "type": rows.where(F.col("p") == config.vocab.type)}.items() if rule == "O10" else [(kind, rows)]:
                found = self._made(rule, k)
                passed.setdefault(k, []).append((None if found is None else {x for x, _ in found}, part.withColumn("by", F.lit(rule))))
                if names is not None:
                    made[k] = _both(made.get(k, set()), found)
        return self._settle(name, outs, number, began) if outs else {}

    def _reads(self, rule: str, kind: str, names: set[str] | None) -> bool:
        """Whether a rule can match triples of a kind with these names."""
        if names is None or rule in ("O6", "O10"):
            return True
        ones = ("R3", "O3", "O7a", "O7b") if rule == "R3+O3+O7" else (rule,)
        return any(k == kind and (x is None or bool(x & names)) for one in ones for k, x in self.schema.wanted(self.config.rule_set[one]))

    def _keep(self, rows: DataFrame) -> Stored:
        """Rows with their bucket, dealt by it where there may be many."""
        return store(placed(rows, self.config.vocab), "b" if self.large else None)

    def _made(self, rule: str, kind: str) -> set[tuple[str, str]] | None:
        """Names of what a rule can derive."""
        out: set[tuple[str, str]] | None = set()
        for one in ("R3", "O3", "O7a", "O7b") if rule == "R3+O3+O7" else (rule,):
            reach = self.schema.reach(self.config.rule_set[one])
            out = _both(out, None if reach is None else {(x, rule) for x in reach[kind == "type"]})
        return out

    def _reachable(self, rules: list[str]) -> tuple[set[str], set[str]] | None:
        """(predicates, classes) of known triples that a stage's results can repeat; None: any."""
        v, predicates, classes = self.config.vocab, set(), set()
        facts = self.names["fact"]
        for r in rules:
            if r in RENAMES and facts is not None and self.schema.local(self.config.rule_set[r]) is not None:
                predicates |= {q for _, q in self._renamed(r, {x for x, _ in facts} | predicates)}
                if v.type in predicates:
                    return None
                continue
            for one in ("R3", "O3", "O7a", "O7b") if r == "R3+O3+O7" else (r,):
                reach = self.schema.reach(self.config.rule_set[one])
                if reach is None:
                    return None
                predicates |= reach[0]
                classes |= reach[1]
        if len(predicates) + len(classes) > MAX_NAMES:
            return None
        return predicates - {v.type}, classes

    def _known(self, names: tuple[set[str], set[str]] | None) -> DataFrame:
        """Known triples of these predicates and classes; None: all."""
        parts = [self.known[k] if names is None else narrowed(self.known[k], names[k == "type"], "o" if k == "type" else "p") for k in sorted(self.present)]
        return reduce(DataFrame.union, [x.select("s", "p", "o") for x in parts])

    def _renamed(self, rule: str, facts: set[str]) -> set[tuple[str, str]]:
        """(predicate, predicate of the consequence) of a renaming rule over these predicates."""
        columns, rows = self.schema.local(self.config.rule_set[rule])
        a, b = (columns.index(x) for x in RENAMES[rule])
        return {(r[a], r[b]) for r in rows if r[a] in facts}

    def sole(self, rules: list[str]) -> set[str]:
        """Predicates of which a stage's results neither repeat nor are known: one rule made them, from one predicate whose
        triples it read once each.  ``rules``: those that gave rows, in their order."""
        v, known = self.config.vocab, self.names["fact"]
        if known is None:
            return set()
        known = {x for x, _ in known}
        sources: dict[str, int] = {}
        out: set[str] = set()
        for rule in rules:
            if rule in RENAMES and self.schema.local(self.config.rule_set[rule]) is not None:
                pairs = self._renamed(rule, known | set(sources))
                clean = {p for p in known if p not in sources} | out
                into: dict[str, list[str]] = {}
                for p, q in pairs:
                    into.setdefault(q, []).append(p)
                for q, froms in into.items():
                    single = len(froms) == 1 and froms[0] in clean and q not in known and q not in sources
                    out = out | {q} if single else out - {q}
                    sources[q] = sources.get(q, 0) + len(froms)
                continue
            for one in ("R3", "O3", "O7a", "O7b") if rule == "R3+O3+O7" else (rule,):
                reach = self.schema.reach(self.config.rule_set[one])
                if reach is None:
                    return set()
                out -= reach[0]
                sources |= {q: sources.get(q, 0) + 1 for q in reach[0]}
        return out - {v.type, v.identity, *v.schema_predicates()}

    def first_seen(self, outs: list[tuple[str, DataFrame]], total: int | None = None) -> DataFrame:
        """s, p, o, n: each triple that was not known, with the number of the first rule that derived it.  total: number of rows, where known."""
        apart = self._apart(outs)
        if apart is not None:
            rest = [x for k, x in enumerate(outs) if k != apart]
            alone = outs[apart][1].select("s", "p", "o", F.lit(apart).alias("n"))
            if not rest:
                return alone
            met = self._first_seen(rest, total and total - self.gained)
            return met.withColumn("n", F.when(F.col("n") >= apart, F.col("n") + 1).otherwise(F.col("n"))).union(alone)
        return self._first_seen(outs, total)

    def _apart(self, outs: list[tuple[str, DataFrame]]) -> int | None:
        """The number of O4 among the rules, if no rule after it can repeat its results.  They hold neither what it read, nor
        what is known: all known triples of its predicates were among its edges or closed."""
        at = next((k for k, (r, _) in enumerate(outs) if r == "O4"), None)
        if at is None:
            return None
        named = self.schema.reach(self.config.rule_set["O4"])
        for r in (x for rule, _ in outs[at + 1 :] for x in (("R3", "O3", "O7a", "O7b") if rule == "R3+O3+O7" else (rule,))):
            reach = self.schema.reach(self.config.rule_set[r])
            if named is None or reach is None or reach[0] & named[0]:
                return None
        return at

    def _first_seen(self, outs: list[tuple[str, DataFrame]], total: int | None) -> DataFrame:
        sole = self.sole([r for r, _ in outs]) if total is not None and total > FEW_RESULTS else set()
        marked = [rows.select("s", "p", "o", F.lit(k).alias("n")) for k, (_, rows) in enumerate(outs)]
        if not sole:
            return self._met(reduce(DataFrame.union, marked), outs, total)
        made = [k for k, (r, _) in enumerate(outs) if r in RENAMES]
        alone = reduce(DataFrame.union, [marked[k].where(F.col("p").isin(*sorted(sole))) for k in made])
        rest = [x.where(~F.col("p").isin(*sorted(sole))) if k in made else x for k, x in enumerate(marked)]
        return self._met(reduce(DataFrame.union, rest), outs, total).union(alone)

    def _met(self, marked: DataFrame, outs: list[tuple[str, DataFrame]], total: int | None) -> DataFrame:
        """``marked`` (s, p, o, n) without repeats and known triples."""
        if not self.present:
            return marked.groupBy("s", "p", "o").agg(F.min("n").alias("n"))
        few = total if total is not None else marked.limit(FEW_RESULTS + 1).count() if self.config.broadcast else None
        names = self._reachable([r for r, _ in outs])
        if few is not None and few <= FEW_RESULTS:
            names = self._names_like(marked) or names
        old = self._known(names)
        if self.config.broadcast and few <= FEW_RESULTS:
            one = marked.groupBy("s", "p", "o").agg(F.min("n").alias("n"))
            again = old.join(F.broadcast(one.select("s", "p", "o")), ["s", "p", "o"], "left_semi")
            return one.join(F.broadcast(again), ["s", "p", "o"], "left_anti")
        every = marked.union(old.withColumn("n", F.lit(-1)))
        return every.groupBy("s", "p", "o").agg(F.min("n").alias("n")).where("n >= 0")

    def _names_like(self, rows: DataFrame) -> tuple[set[str], set[str]] | None:
        """(predicates, classes) of ``rows`` that are known; None where there are too many."""
        found = classify(rows, self.config.vocab).select("kind", self._name().alias("name")).distinct().limit(MAX_NAMES + 1).collect()
        if len(found) > MAX_NAMES:
            return None
        known: tuple[set[str], set[str]] = (set(), set())
        for r in found:
            names = self.names.get(r["kind"], set())
            if r["name"] is not None and (names is None or any(x == r["name"] for x, _ in names)):
                known[r["kind"] == "type"].add(r["name"])
        return known

    def _settle(self, name: str, outs: list[tuple[str, Stored]], number: int, began: float) -> dict[str, DataFrame]:
        """One removal of repeats and known triples for the whole stage."""
        frames = [(r, x.frame) for r, x in outs]
        self.gained = sum(x.rows for r, x in outs if r == "O4")
        apart = self._apart(frames)
        kept = self._keep(classify(self.first_seen(frames, sum(x.rows for _, x in outs)), self.config.vocab))
        for k, (rule, x) in enumerate(outs):
            if rule == "O4":  # from the stage's results, where all of it is among them
                rows = x.frame if apart is None else kept.frame.where(F.col("n") == k)
                self.closed = self.closed.union(rows.select("p", F.col("s").alias("src"), F.col("o").alias("dst")))
            if rule == "O4" and apart is None:
                self.stored.append(x)
            else:
                x.forget()
        self.stored.append(kept)
        fresh = kept.frame
        # The schema bounds the names that rules can derive; where it does not, they are not gathered.
        named = self._reachable([r for r, _ in outs]) is not None
        rows = fresh.groupBy("kind", "n", (self._name() if named else F.lit("")).alias("name")).agg(F.count("*").alias("m")).collect()
        counts: dict[tuple[str, int], int] = {}
        for r in rows:
            counts[r["kind"], r["n"]] = counts.get((r["kind"], r["n"]), 0) + r["m"]
            if r["kind"] != "schema":
                self.found_names[r["kind"]] = _both(self.found_names.get(r["kind"], set()), {(r["name"], outs[r["n"]][0])} if named else None)
        for k, x in self.found_names.items():
            self.names[k] = _both(self.names[k], None if x is None else {(name, "") for name, _ in x})
        raw = {k: x.rows for k, (_, x) in enumerate(outs)} if self.config.count_raw else {}
        secs = time.time() - began
        for k, (rule, _) in enumerate(outs):
            self.stats.append((number, name, rule, raw.get(k), sum(m for (_, n), m in counts.items() if n == k), secs / len(outs)))
        names = F.element_at(F.array(*[F.lit(r) for r, _ in outs]), F.col("n") + 1)
        found = {}
        for kind in sorted({k for k, _ in counts}):
            rows = fresh.where(F.col("kind") == kind).select(*KNOWN, names.alias("by"))
            if kind == "schema":  # a fact rule may reach schema vocabulary
                more = schema_rows(rows.select("s", "p", "o")) - self.schema_set
                if more:
                    self.schema_set = close_schema(self.schema_set | more, self.config)
                    self.schema, self.closed = self._schema(), None
                    found["schema"] = rows
                continue
            found[kind] = rows
            plain = rows.select(*KNOWN)
            self.known[kind] = self.known[kind].union(plain) if kind in self.present else plain
            self.present.add(kind)
        self.derived.append(fresh.where("kind <> 'schema'").select("s", "p", "o", names.alias("rule"), F.lit(number).alias("round")))
        return found

    def _fused(self, facts: DataFrame | None) -> DataFrame | None:
        rewrites = sorted(property_rewrites(sorted(self.schema_set), self.config.vocab))
        if facts is None or not rewrites:
            return None
        return fused_facts(facts, self.spark.createDataFrame(rewrites, "p string, q string, swap boolean"), len(rewrites))

    def transitive_edges(self, facts: DataFrame) -> DataFrame:
        rule = self.config.rule_set["O4"]
        named = self.schema.side(rule).select(F.col("v_p").alias("p"))
        if self.large:  # the files are dealt; elsewhere all of them are read anyway
            facts = narrowed(facts, self.schema.wanted(rule)[0][1])
        return facts.join(named, "p", "left_semi").select("p", F.col("s").alias("src"), F.col("o").alias("dst"))

    def _transitive(self, full: dict[str, DataFrame], new: dict[str, DataFrame] | None, files: list[Stored]) -> DataFrame | None:
        """The pairs that transitivity adds; the edges themselves are known or came from the rules before.  files: takes what they are made from."""
        bound = self.schema.bindings(self.config.rule_set["O4"])
        facts = full.get("fact")
        if bound[1] == 0 or facts is None or new is not None and "fact" not in new:
            return None
        if new is None or self.closed is None:
            edges = store(self.transitive_edges(facts).distinct())
            if edges.rows == 0:
                edges.forget()
                return None
            rest = close_relation(edges.frame, self.config.closure_method, partitions=self.config.closure_partitions, kept=files, beyond=True)
            self.closed = None
        else:
            found = extension(self.closed, self.transitive_edges(new["fact"]))
            if found is None:
                return None
            edges, rest, more = found
            files += more
        self.stored.append(edges)
        self.closings.append(edges.rows)
        self.closed = edges.frame if self.closed is None else self.closed.union(edges.frame)
        return rest.select(F.col("src").alias("s"), "p", F.col("dst").alias("o"))

    def _pairs(self, full: dict[str, DataFrame]) -> DataFrame | None:
        same = full.get("identity")
        return None if same is None else pair_closure(same, self.config.vocab)

    def loop(self, began: dict[str, DataFrame] | None = None, first: int = 1, began_names: Names | None = None) -> int:
        """fact and type stages until neither finds anything new after ``began`` (everything known, if not given); returns the number of
        the last round.  began_names: what ``began`` names, where that is known."""
        stages = self.config.plan.loop
        start = self.everything() if began is None else began
        pending: dict[str, dict[str, list[DataFrame]]] = {s.cls: {k: [x] for k, x in start.items()} for s in stages}
        names: dict[str, Names] = {s.cls: dict(self.names if began is None else began_names or dict.fromkeys(start)) for s in stages}
        schema = self.schema
        for number in range(first, first + self.config.max_rounds):
            quiet = True
            for s in stages:
                mine, pending[s.cls] = pending[s.cls], {}
                named, names[s.cls] = names[s.cls], {}
                if not mine and (number > first or began is not None):
                    continue
                schema_before = self.schema
                # In the first round a stage has all that is known before it.
                found = self.stage(s.cls, s.rules, self._parts(mine) if self.config.delta else None, number, named, began is None and number == first and self.schema is schema)
                if self.schema is not schema_before:  # new schema meets all old facts
                    found = self.everything()
                    for other in stages:
                        pending[other.cls], names[other.cls] = {k: [x] for k, x in found.items()}, dict(self.names)
                    quiet = False
                    continue
                if found:
                    quiet = False
                    for other in stages:
                        for k, x in found.items():
                            # A stage sees its own results in its pass, but not those of rules before their producers.
                            pending[other.cls].setdefault(k, []).append(x)
                            names[other.cls][k] = _both(names[other.cls].get(k, set()), self.found_names.get(k))
            if quiet:
                return number
        raise RuntimeError(f"no fixpoint in {self.config.max_rounds} rounds")

    def identity(self, number: int) -> dict[str, DataFrame]:
        return self.stage("identity", self.config.plan.identity.rules + (MERGING if self.config.include_merging_rules else ()), None, number)

    def whole(self, rounds: int) -> int:
        """Identity and loop stages in turn until identity adds nothing; returns the number of the last round."""
        for _ in range(self.config.max_rounds):
            schema_before, found = self.schema, self.identity(rounds + 1)
            if not found:
                return rounds
            rounds = self.loop(None if self.schema is not schema_before else found, rounds + 2)
        raise RuntimeError(f"no fixpoint in {self.config.max_rounds} identity rounds")

    def links(self) -> DataFrame | None:
        """Asserted identity, and what functional and inverse functional properties make identical, each term linked to the smallest
        of its group: linear, with the same cliques as all pairs."""
        out = [self.known["identity"].select("s", "o")] if "identity" in self.present else []
        if "fact" in self.present:
            for rule, key, term in (("O1", "s", "o"), ("O2", "o", "s")):
                r = self.config.rule_set[rule]
                if self.config.uses(rule) and self.schema.bindings(r)[1]:
                    named = self.schema.side(r).select(F.col("v_p").alias("p"))
                    out.append(star_pairs(narrowed(self.known["fact"], self.schema.wanted(r)[0][1]).join(named, "p", "left_semi"), key, term, self.config.vocab).select("s", "o"))
        links = cut(reduce(DataFrame.union, out).where("s <> o")) if out else None
        return None if links is None or links.isEmpty() else links


def _canonical(run: Run, rounds: int) -> tuple[Run, int, DataFrame | None]:
    """Terms, values that restrictions require among them, become the representatives of their cliques and the rules run over
    these, until no two representatives are found identical."""
    reps, derived, stats = None, list(run.derived), list(run.stats)
    for _ in range(run.config.max_rounds):
        links = run.links()
        if links is None:
            run.derived, run.stats = derived, stats
            return run, rounds, reps
        more = canonicalize(links)
        if reps is None:
            reps = more
        else:
            to = more.select(F.col("term").alias("t"), F.col("rep").alias("r"))
            old = reps.join(to, F.col("rep") == F.col("t"), "left").select("term", F.coalesce("r", "rep").alias("rep"))
            reps = cut(old.union(more.join(reps, "term", "left_anti")))
        has_value = run.config.vocab.has_value
        named = run.spark.createDataFrame(sorted({(x,) for s, _, o in run.schema_set for x in (s, o)}), "term string")
        moved = {r["term"]: r["rep"] for r in more.where("term <> rep").join(F.broadcast(named), "term").collect()}  # no more than the schema holds
        found = None if moved else _moved(run, more)
        if found is not None:
            run, new, names = found
            rounds = run.loop(new, rounds + 1, names) if new else rounds
            derived += run.derived
            stats += run.stats
            continue
        # The schema names what moved, so all rules run anew over everything.
        parts = [rewrite(run.known[k], more) for k in ("type", "fact") if k in run.present]
        schema = sorted({(s, p, moved.get(o, o) if p == has_value else o) for s, p, o in run.schema_set})
        rows = reduce(DataFrame.union, [run.spark.createDataFrame(schema, TRIPLE), *parts])
        before, run = run, Run(rows, run.config)
        run.asserted, run.stored = before.asserted, before.stored + run.stored
        rounds = run.loop(None, rounds + 1)
        derived += run.derived
        stats += run.stats
    raise RuntimeError(f"no fixpoint in {run.config.max_rounds} identity rounds")


def _not_in(new: Stored, known: DataFrame, broadcast: bool) -> DataFrame:
    """Triples that are not known; where they are few, only those of the known ones that repeat them move."""
    few = broadcast and new.rows <= FEW_RESULTS
    again = known.join(F.broadcast(new.frame.select("s", "p", "o")), ["s", "p", "o"], "left_semi") if few else known
    return new.frame.join(F.broadcast(again) if few else again, ["s", "p", "o"], "left_anti")


def _moved(before: Run, reps: DataFrame) -> tuple[Run, dict[str, DataFrame], Names] | None:
    """(a run over representatives; what is new to it, and its names): the triples that hold another term than before.  Those that stay
    are closed among themselves.  None where a triple that moved says something about the schema."""
    config = before.config
    moves = store(reps.where("term <> rep"))
    side = F.broadcast if config.broadcast and moves.rows <= FEW_RESULTS else (lambda x: x)
    s, o = (side(moves.frame.select(F.col("term").alias(f"t{c}"), F.col("rep").alias(f"r{c}"))) for c in "so")
    kinds = [k for k in ("type", "fact") if k in before.present]
    rows = reduce(DataFrame.union, [before.known[k].withColumn("kind", F.lit(k)) for k in kinds])
    rows = rows.join(s, F.col("s") == F.col("ts"), "left").join(o, F.col("o") == F.col("to"), "left")
    touched = F.col("rs").isNotNull() | F.col("ro").isNotNull()
    whole = before._keep(rows.select(F.coalesce("rs", "s").alias("s"), "p", F.coalesce("ro", "o").alias("o"), "kind", touched.alias("touched")))
    moves.forget()
    stay = whole.frame.where("not touched")
    asked = store(whole.frame.where("touched").select("s", "p", "o").distinct())
    fresh = before._keep(classify(_not_in(asked, stay.select("s", "p", "o"), config.broadcast), config.vocab))
    asked.forget()
    if not fresh.frame.where("kind = 'schema'").isEmpty():
        whole.forget()
        fresh.forget()
        return None
    run = Run.after(before, {k: stay.where(F.col("kind") == k).select(*KNOWN) for k in kinds}, {**dict.fromkeys(("type", "fact", "identity"), set()), **{k: before.names[k] for k in kinds}}, config)
    run.asserted = before.asserted
    run.stored += [whole, fresh]
    if "fact" in run.present and run.schema.bindings(config.rule_set["O4"])[1] and config.uses("O4"):
        run.closed = run.transitive_edges(run.known["fact"])
    names = run._names(fresh.frame)
    new = {k: fresh.frame.where(F.col("kind") == k).select(*KNOWN).withColumn("by", F.lit("")) for k in kinds if names[k] is None or names[k]}
    run.arrived(new, names)
    return run, new, names


def reason(triples: DataFrame, config: Config | None = None) -> ReasonResult:
    """The closure of ``triples`` under the configured rules."""
    config = config or Config()
    run = Run(triples, config)
    rounds, reps = run.loop(), None
    if config.identity_mode == "final":
        run.identity(rounds + 1)
    elif config.identity_mode == "fixpoint":
        rounds = run.whole(rounds)
    elif config.identity_mode == "canonical":
        run, rounds, reps = _canonical(run, rounds)
    schema = run.spark.createDataFrame(sorted(run.schema_set), TRIPLE)
    kinds = ("type", "fact") if reps is not None else ("type", "identity", "fact")
    parts = [run.known[k].select("s", "p", "o") for k in kinds if k in run.present]
    closure = reduce(DataFrame.union, [schema, *parts])
    made = run.spark.createDataFrame(sorted(run.schema_set - run.asserted), TRIPLE).select("s", "p", "o", F.lit("schema").alias("rule"), F.lit(0).alias("round"))
    derived = reduce(DataFrame.union, [made, *run.derived])
    return ReasonResult(closure, derived if config.provenance else derived.select("s", "p", "o"), schema, rounds, run.stats, reps, run.stored, run)


def reason_incremental(delta: DataFrame, closed: ReasonResult, config: Config | None = None) -> ReasonResult:
    """The closure after ``delta`` arrived, from one that was complete without it.

    Complete means by the loop rules, and by those of identity too with ``fixpoint``; the other identity modes have no
    closure to go on from, and identity is left out.  Schema among what arrives closes everything again; schema that rules derive meets
    all that is known.  The result shares the files of ``closed``: only the last of a row of results may forget them.
    """
    config = config or Config()
    config = config if config.identity_mode == "fixpoint" else replace(config, identity_mode="off")
    before = closed.run
    if before is not None and before.config.vocab == config.vocab and closed.reps is None and len(closed.stored) <= MANY_FILES:
        run = Run.after(before, dict(before.known), dict(before.names), config)
        run.known, run.present = {k: x for k, x in run.known.items() if k in before.present}, set(before.present)
    else:
        run = Run(closed.closure, config)
        run.known = {k: x for k, x in run.known.items() if k in run.present}
    arriving = store(delta.select("s", "p", "o").distinct())
    run.large = run.large or arriving.rows > FEW_RESULTS
    kept = run._keep(classify(_not_in(arriving, closed.closure, config.broadcast), config.vocab))
    arriving.forget()
    run.stored.append(kept)
    more = kept.frame
    new_schema = schema_rows(more.where("kind = 'schema'").select("s", "p", "o"))
    if new_schema:
        kept.forget()
        return reason(closed.closure.union(delta.select("s", "p", "o")), config)
    if "fact" in run.present and run.schema.bindings(config.rule_set["O4"])[1] and config.uses("O4"):
        run.closed = run.transitive_edges(run.known["fact"])
    named = run._names(more)
    new = {k: more.where(F.col("kind") == k).select(*KNOWN).withColumn("by", F.lit("")) for k in ("type", "identity", "fact") if named[k] is None or named[k]}
    run.arrived(new, named)
    rounds = run.loop(new, began_names=named) if new else 0
    if new and config.identity_mode == "fixpoint":
        rounds = run.whole(rounds)
    schema = run.spark.createDataFrame(sorted(run.schema_set), TRIPLE)
    closure = reduce(DataFrame.union, [schema, *[run.known[k].select("s", "p", "o") for k in ("type", "identity", "fact") if k in run.present]])
    derived = reduce(DataFrame.union, [d.select("s", "p", "o") for d in run.derived]) if run.derived else closure.limit(0)
    return ReasonResult(closure, derived, schema, rounds, run.stats, None, run.stored, run)
