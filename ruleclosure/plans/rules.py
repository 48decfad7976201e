"""The 27 entailment rules as data: premises, consequence, class.

Terms that begin with ``?`` are variables.  A premise's kind follows from its predicate: vocabulary predicates and
memberships of vocabulary classes are schema, other memberships are types, the identity predicate is identity,
and a variable predicate stands for facts.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from ..vocab import VOCAB, Vocabulary


@dataclass(frozen=True)
class Atom:
    s: str
    p: str
    o: str

    def terms(self) -> tuple[str, str, str]:
        return self.s, self.p, self.o

    def variables(self) -> list[str]:
        return list(dict.fromkeys(t for t in self.terms() if t.startswith("?")))

    def kind(self, vocab: Vocabulary = VOCAB) -> str:
        if self.p in vocab.schema_predicates() or self.p == vocab.type and self.o in vocab.schema_classes():
            return "schema"
        if self.p == vocab.type:
            return "type"
        return "identity" if self.p == vocab.identity else "fact"


@dataclass(frozen=True)
class Rule:
    id: str
    body: tuple[Atom, ...]
    head: Atom
    #: Variables that must differ, or the consequence would only say that a term is itself.
    differ: tuple[str, str] | None = None

    def instance_premises(self, vocab: Vocabulary = VOCAB) -> int:
        return sum(a.kind(vocab) != "schema" for a in self.body)

    def cls(self, vocab: Vocabulary = VOCAB) -> str:
        """identity, type, fact or schema, by the kinds of premises and consequence."""
        kinds = {a.kind(vocab) for a in (*self.body, self.head)}
        return next(k for k in ("identity", "type", "fact", "schema") if k in kinds)


def build(vocab: Vocabulary = VOCAB) -> dict[str, Rule]:
    v = vocab
    lines = {
        "R1": (("?a ?b", v.sub_class), ("?b ?c", v.sub_class), "->", ("?a ?c", v.sub_class), "?a ?c"),
        "R2": (("?a ?b", v.sub_property), ("?b ?c", v.sub_property), "->", ("?a ?c", v.sub_property), "?a ?c"),
        "R3": (("?x ?y", "?p"), ("?p ?q", v.sub_property), "->", ("?x ?y", "?q")),
        "R4": (("?p ?c", v.domain), ("?x ?y", "?p"), "->", ("?x ?c", v.type)),
        "R5": (("?p ?c", v.range), ("?x ?y", "?p"), "->", ("?y ?c", v.type)),
        "R6": (("?c ?d", v.sub_class), ("?x ?c", v.type), "->", ("?x ?d", v.type)),
        "O1": ((f"?p {v.functional}", v.type), ("?x ?y", "?p"), ("?x ?z", "?p"), "->", ("?y ?z", v.identity), "?y ?z"),
        "O2": ((f"?p {v.inverse_functional}", v.type), ("?y ?x", "?p"), ("?z ?x", "?p"), "->", ("?y ?z", v.identity), "?y ?z"),
        "O3": ((f"?p {v.symmetric}", v.type), ("?x ?y", "?p"), "->", ("?y ?x", "?p")),
        "O4": ((f"?p {v.transitive}", v.type), ("?x ?y", "?p"), ("?y ?z", "?p"), "->", ("?x ?z", "?p")),
        "O5": (("?x ?y", v.identity), "->", ("?y ?x", v.identity)),
        "O6": (("?x ?y", v.identity), ("?y ?z", v.identity), "->", ("?x ?z", v.identity), "?x ?z"),
        "O7a": (("?p ?q", v.inverse), ("?x ?y", "?p"), "->", ("?y ?x", "?q")),
        "O7b": (("?p ?q", v.inverse), ("?x ?y", "?q"), "->", ("?y ?x", "?p")),
        "O8": ((f"?a {v.class_term}", v.type), ("?a ?b", v.identity), "->", ("?a ?b", v.sub_class)),
        "O9": ((f"?a {v.property_term}", v.type), ("?a ?b", v.identity), "->", ("?a ?b", v.sub_property)),
        "O10": (("?x ?y", "?p"), ("?x ?u", v.identity), ("?y ?w", v.identity), "->", ("?u ?w", "?p")),
        "O11a": (("?a ?b", v.equivalent_class), "->", ("?a ?b", v.sub_class)),
        "O11b": (("?a ?b", v.equivalent_class), "->", ("?b ?a", v.sub_class)),
        "O11c": (("?a ?b", v.sub_class), ("?b ?a", v.sub_class), "->", ("?a ?b", v.equivalent_class), "?a ?b"),
        "O12a": (("?a ?b", v.equivalent_property), "->", ("?a ?b", v.sub_property)),
        "O12b": (("?a ?b", v.equivalent_property), "->", ("?b ?a", v.sub_property)),
        "O12c": (("?a ?b", v.sub_property), ("?b ?a", v.sub_property), "->", ("?a ?b", v.equivalent_property), "?a ?b"),
        "O13": (("?c ?w", v.has_value), ("?c ?p", v.on_property), ("?x ?w", "?p"), "->", ("?x ?c", v.type)),
        "O14": (("?c ?w", v.has_value), ("?c ?p", v.on_property), ("?x ?c", v.type), "->", ("?x ?w", "?p")),
        "O15": (("?c ?f", v.some_values), ("?c ?p", v.on_property), ("?x ?y", "?p"), ("?y ?f", v.type), "->", ("?x ?c", v.type)),
        "O16": (("?c ?f", v.all_values), ("?c ?p", v.on_property), ("?x ?y", "?p"), ("?x ?c", v.type), "->", ("?y ?f", v.type)),
    }
    atom = lambda ends, p: Atom(*ends.split()[:1], p, ends.split()[1])
    out = {}
    for name, line in lines.items():
        arrow = line.index("->")
        rest = line[arrow + 2 :]
        out[name] = Rule(name, tuple(atom(*x) for x in line[:arrow]), atom(*line[arrow + 1]), tuple(rest[0].split()) if rest else None)
    return out


RULES = build()
#: Rules that merge ontologies; off unless asked for.
MERGING = ("O8", "O9")


def as_printed(rules: dict[str, Rule] = RULES) -> dict[str, Rule]:
    """The published wording of the two value rules, in which the restriction class stands for the required value."""
    o13, o14 = rules["O13"], rules["O14"]
    return rules | {
        "O13": replace(o13, body=(*o13.body[:2], Atom("?x", "?p", "?c"))),
        "O14": replace(o14, head=Atom("?x", "?p", "?c")),
    }


def classify_rules(rules: dict[str, Rule] = RULES, vocab: Vocabulary = VOCAB) -> dict[str, list[str]]:
    """fact, type, identity and schema rules.  A rule whose consequence is schema but that reads identity counts as identity."""
    out: dict[str, list[str]] = {k: [] for k in ("fact", "type", "identity", "schema")}
    for r in rules.values():
        out[r.cls(vocab)].append(r.id)
    return out


def conjunctive_sql(rule: Rule, source: str, vocab: Vocabulary = VOCAB) -> str:
    """The rule as one SELECT over a relation (s, p, o): a plain reading, for other engines and tests."""
    words = ", ".join(f"'{w}'" for w in (*vocab.schema_predicates(), vocab.type, vocab.identity))
    classes = ", ".join(f"'{w}'" for w in vocab.schema_classes())
    where, seen, tables = [], {}, []
    for k, a in enumerate(rule.body):
        tables.append(f"{source} t{k}")
        for column, term in zip("spo", a.terms(), strict=True):
            place = f"t{k}.{column}"
            if term.startswith("?"):
                if term in seen:
                    where.append(f"{seen[term]} = {place}")
                seen.setdefault(term, place)
            else:
                where.append(f"{place} = '{term}'")
        if a.p.startswith("?") and rule.id == "O10":  # types are restated too
            where.append(f"t{k}.p NOT IN ({words.replace(repr(vocab.type), repr(vocab.identity))})")
            where.append(f"NOT (t{k}.p = '{vocab.type}' AND t{k}.o IN ({classes}))")
        elif a.p.startswith("?"):
            where.append(f"t{k}.p NOT IN ({words})")
    if rule.differ:
        where.append(f"{seen[rule.differ[0]]} <> {seen[rule.differ[1]]}")
    head = [seen.get(t, f"'{t}'") for t in rule.head.terms()]
    return f"SELECT {head[0]} AS s, {head[1]} AS p, {head[2]} AS o FROM {', '.join(tables)}" + (f" WHERE {' AND '.join(where)}" if where else "")
