"""Mixing sources to target weights by hierarchical budgeting.

Weights belong to the nodes of a domain - language - source tree.  A token budget goes down the tree: each node's
children share its budget by weight, no child gets more than its subtree can give (its tokens times
``max_epochs``), and what one can't use goes to its siblings before the parent's siblings see any of it, since a
parent's own budget never exceeds its capacity.  Shares come in closed form from running sums over siblings in order
of capacity per weight; all amounts are integers.

A leaf takes whole epochs as long as its budget covers them and then a prefix of one more, seeded, epoch: rows in
order of md5(seed:epoch:doc_id), up to the last that fits.  The end of the prefix is found digit by digit: sums over 256 buckets of
the hash name the bucket it lies in, that bucket is split by the next two digits, and so on until no leaf has more than
``FEW`` different hashes left in its bucket.  So no task holds more than a few hundred rows of a leaf; after that, selecting is a
comparison in each row.

Edge cases: null domain, language or source is a node of its own; a null or empty text has no tokens and
comes with its leaf's epochs; rows with one doc_id come in or stay out together; nodes with weight 0 get nothing, and what they
hold counts for no capacity; an empty table gives an empty result.  Input columns stay as they are, whatever their names; the
added ones take underscores where a name is taken.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from ..durable import cut
from .common import free_name

LEVELS = ("domain", "lang", "source")
WORDS = r"[^\x20\x09-\x0D]+"
MAX_BROADCAST_LEAVES = 100_000
#: Different hashes of a border bucket that are ranked at once, and hash digits a step.
FEW, DIGITS = 512, 2


@dataclass(frozen=True)
class Recipe:
    """Weights by level (a name not listed has ``default``), the budget as a share of all tokens in percent."""

    weights: dict[str, dict[str, int]] = field(default_factory=dict)
    default: int = 10
    budget_percent: int = 60
    max_epochs: int = 2
    seed: int = 17
    domain_sql: str = "CASE WHEN source IS NULL THEN NULL ELSE concat('d', cast(length(source) AS string), right(source, 1)) END"


RECIPE = Recipe(
    weights={
        "domain": {"web": 50, "news": 20, "forum": 10, "reference": 20},
        "lang": {"en": 60, "de": 15, "fr": 15, "es": 10},
        "source": {"src0": 5, "src1": 20},
    },
    domain_sql="CASE WHEN source IN ('src0', 'src4', 'src8', 'src12', 'src16') THEN 'web' WHEN source IN ('src1', 'src5', 'src9', 'src13', 'src17') THEN 'news'"
    " WHEN source IN ('src2', 'src6', 'src10', 'src14', 'src18') THEN 'forum' ELSE 'reference' END",
)


def _case(level: str, recipe: Recipe) -> str:
    arms = " ".join(f"WHEN {level} = '{k}' THEN {v}" for k, v in recipe.weights.get(level, {}).items())
    return f"CASE {arms} ELSE {recipe.default} END" if arms else str(recipe.default)


def share(children: DataFrame, parent: list[str], budget: F.Column) -> DataFrame:
    """``children`` (key columns, weight, cap) with ``give``: what each gets of its parent's ``budget``."""
    keys = [F.col(c) for c in parent] or [F.lit(0)]
    order = W.Window.partitionBy(*keys).orderBy(F.col("cap") / F.col("weight"), *[F.asc_nulls_first(c) for c in LEVELS if c in children.columns])
    before, after = order.rowsBetween(W.Window.unboundedPreceding, -1), order.rowsBetween(0, W.Window.unboundedFollowing)
    staged = children.withColumn("budget_", budget).where("weight > 0")
    staged = staged.withColumn("left_", F.col("budget_") - F.coalesce(F.sum("cap").over(before), F.lit(0))).withColumn("weight_", F.sum("weight").over(after))
    full = F.expr("CAST(left_ AS decimal(20,0)) * CAST(weight AS decimal(18,0)) >= CAST(cap AS decimal(20,0)) * CAST(weight_ AS decimal(18,0))")
    staged = staged.withColumn("full_", full)
    all_of = W.Window.partitionBy(*keys)
    staged = staged.withColumn("spent_", F.sum(F.when(F.col("full_"), F.col("cap")).otherwise(0)).over(all_of)).withColumn("open_", F.sum(F.when(F.col("full_"), 0).otherwise(F.col("weight"))).over(all_of))
    part = F.expr("CAST(floor(CAST(budget_ - spent_ AS decimal(20,0)) * CAST(weight AS decimal(10,0)) / CAST(nullif(open_, 0) AS decimal(8,0))) AS bigint)")
    return staged.withColumn("give", F.when(F.col("full_"), F.col("cap")).otherwise(part)).drop("budget_", "left_", "weight_", "full_", "spent_", "open_")


def leaf_budgets(leaves: DataFrame, recipe: Recipe, budget: int) -> DataFrame:
    """domain, lang, source, tokens, give for each leaf (``leaves``: the three names and tokens)."""
    closed = " OR ".join(f"({_case(x, recipe)}) = 0" for x in LEVELS)
    weighed = leaves.select("*", F.expr(f"CASE WHEN {closed} THEN 0 ELSE tokens * {recipe.max_epochs} END").alias("cap"))
    total, parent = F.lit(budget).cast("bigint"), []
    given = None
    for k, level in enumerate(LEVELS):
        names = list(LEVELS[: k + 1])
        children = weighed.groupBy(*names).agg(F.sum("cap").alias("cap"), F.sum("tokens").alias("tokens")).withColumn("weight", F.expr(_case(level, recipe)).cast("bigint"))
        if given is not None:
            up = given.select(*[F.col(c).alias(f"{c}_up") for c in parent], F.col("give").alias("from_above"))
            on = [F.col(c).eqNullSafe(F.col(f"{c}_up")) for c in parent]
            children = children.join(up, on).drop(*[f"{c}_up" for c in parent])
            given = share(children, parent, F.col("from_above")).drop("from_above")
        else:
            given = share(children, parent, F.least(total, F.sum("cap").over(W.Window.partitionBy(F.lit(0)))))
        parent = names
    return given.select(*LEVELS, "tokens", "give")


def _prepared(docs: DataFrame, recipe: Recipe) -> DataFrame:
    return docs.select(
        F.expr(recipe.domain_sql).alias("domain"), "lang", "source", F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("id"),
        F.coalesce(F.regexp_count("text", F.lit(WORDS)), F.lit(0)).cast("bigint").alias("tokens"),
    )


def _lot(epoch: F.Column, doc: F.Column, seed: int) -> F.Column:
    return F.md5(F.concat(F.lit(f"{seed}:"), epoch.cast("string"), F.lit(":"), doc).cast("binary"))


def plan(docs: DataFrame, recipe: Recipe = RECIPE) -> DataFrame:
    """One row per leaf: names (prefixed ``mix_``), tokens, give, whole epochs ``full``, and ``upto``, the hash up to
    which rows come once more."""
    rows = cut(_prepared(docs, recipe))
    leaves = cut(rows.groupBy(*LEVELS).agg(F.sum("tokens").alias("tokens")))
    total = leaves.agg(F.coalesce(F.sum("tokens"), F.lit(0))).first()[0]
    given = leaf_budgets(leaves, recipe, int(total) * recipe.budget_percent // 100)
    given = given.select(
        *[F.col(c).alias(f"mix_{c}") for c in LEVELS], F.col("tokens").alias("leaf_tokens"), "give",
        F.expr("CASE WHEN tokens > 0 THEN give div tokens ELSE 0 END").alias("full"), F.expr("CASE WHEN tokens > 0 THEN give % tokens ELSE 0 END").alias("more"),
    )
    given = cut(given)
    small = F.broadcast(given) if given.count() <= MAX_BROADCAST_LEAVES else given
    names = [f"mix_{c}" for c in LEVELS]
    # Rows of one hash, those of one doc_id above all, count as one.
    drawn = rows.join(small, [F.col(c).eqNullSafe(F.col(f"mix_{c}")) for c in LEVELS]).where("more > 0")
    drawn = cut(drawn.groupBy(*names, "more", _lot(F.col("full"), F.col("id"), recipe.seed).alias("lot")).agg(F.sum("tokens").alias("tokens")))
    last = prefix_ends(drawn, names).select(*[F.col(c).alias(f"{c}_l") for c in names], "upto")
    return given.join(last, [F.col(c).eqNullSafe(F.col(f"{c}_l")) for c in names], "left").select(*names, "leaf_tokens", "give", "full", F.coalesce("upto", F.lit("")).alias("upto"))


def prefix_ends(drawn: DataFrame, names: list[str]) -> DataFrame:
    """``names`` and ``upto``, the last hash whose running sum of tokens is within ``more``, for each leaf (drawn: names, more, lot, tokens;
    different lots)."""
    border = drawn.groupBy(*names).agg(F.lit("").alias("prefix"), F.lit(0).cast("bigint").alias("before"), F.count("*").alias("rows"))
    same = lambda: [F.col(c).eqNullSafe(F.col(f"{c}_b")) for c in names]
    for step in range(1, 32 // DIGITS + 1):
        border = cut(border)
        side = border.select(*[F.col(c).alias(f"{c}_b") for c in names], "prefix", "before")
        side = F.broadcast(side) if border.count() <= MAX_BROADCAST_LEAVES else side
        inside = drawn.join(side, [*same(), F.substring("lot", 1, DIGITS * (step - 1)) == F.col("prefix")]).select(*names, "more", "lot", "tokens", "before")
        if (border.agg(F.max("rows")).first()[0] or 0) <= FEW:
            break
        buckets = inside.groupBy(*names, "more", "before", F.substring("lot", 1, DIGITS * step).alias("prefix")).agg(F.sum("tokens").alias("n"), F.count("*").alias("rows"))
        order = W.Window.partitionBy(*names).orderBy("prefix").rowsBetween(W.Window.unboundedPreceding, 0)
        over = buckets.withColumn("run", F.col("before") + F.sum("n").over(order)).where("run > more")
        border = over.groupBy(*names).agg(F.min_by(F.struct("prefix", (F.col("run") - F.col("n")).alias("before"), "rows"), "prefix").alias("b")).select(*names, "b.*")
    order = W.Window.partitionBy(*names).orderBy("lot").rowsBetween(W.Window.unboundedPreceding, 0)
    ranked = inside.withColumn("run", F.sum("tokens").over(order) + F.col("before"))
    # Where nothing of the bucket fits, all hashes before the bucket do; its own digits alone sort before its hashes.
    least = F.min(F.struct("lot")).alias("least")
    return ranked.groupBy(*names).agg(F.max(F.when(F.col("run") <= F.col("more"), F.col("lot"))).alias("fits"), least).select(
        *names, F.coalesce("fits", F.expr("substring(least.lot, 1, length(least.lot) - 1)")).alias("upto")
    )


def select(docs: DataFrame, recipe: Recipe = RECIPE) -> DataFrame:
    """The rows that the mixture takes, with ``domain``, ``tokens`` and ``copies`` (how many epochs hold them)."""
    leaves = cut(plan(docs, recipe))
    small = F.broadcast(leaves) if leaves.count() <= MAX_BROADCAST_LEAVES else leaves
    rows = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.expr(recipe.domain_sql).alias("domain"), "lang", "source",
        F.coalesce(F.regexp_count("text", F.lit(WORDS)), F.lit(0)).cast("bigint").alias("tokens"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("id"),
    )
    met = rows.join(small, [F.col(c).eqNullSafe(F.col(f"mix_{c}")) for c in LEVELS])
    copies = (F.col("full") + (_lot(F.col("full"), F.col("id"), recipe.seed) <= F.col("upto")).cast("bigint")).alias("copies")
    taken = met.select("row", "domain", "tokens", copies).where("copies > 0")
    added = [F.col(c).alias(free_name(c, docs.columns)) for c in ("domain", "tokens", "copies")]
    return taken.select(*[F.col("row")[c].alias(c) for c in docs.columns], *added)


def report(docs: DataFrame, recipe: Recipe = RECIPE) -> DataFrame:
    return select(docs.select("doc_id", "text", "lang", "source"), recipe).select("doc_id", "domain", "lang", "source", "tokens", "copies")


def sql(recipe: Recipe = RECIPE) -> str:
    closed = " OR ".join(f"({_case(x, recipe)}) = 0" for x in LEVELS)

    def level(k: int) -> str:
        names = LEVELS[: k + 1]
        cols, up = ", ".join(names), ", ".join(LEVELS[:k])
        part = f"PARTITION BY {up}" if up else ""
        budget = "least(CAST(total * PCT // 100 AS BIGINT), sum(cap) OVER ())".replace("PCT", str(recipe.budget_percent)) if not k else "from_above"
        source = f"(SELECT {cols}, CAST(sum(CASE WHEN {closed} THEN 0 ELSE tokens END) * {recipe.max_epochs} AS BIGINT) AS cap, CAST(sum(tokens) AS BIGINT) AS tokens FROM leaves GROUP BY ALL)"
        if k:
            on = " AND ".join(f"c.{x} IS NOT DISTINCT FROM u.{x}" for x in LEVELS[:k])
            source = f"(SELECT c.*, u.give AS from_above FROM {source} c JOIN g{k - 1} u ON {on})"
        else:
            source = f"(SELECT c.*, (SELECT sum(tokens) FROM leaves) AS total FROM {source} c)"
        return f"""
a{k} AS (SELECT *, {_case(LEVELS[k], recipe)} AS weight, {budget} AS b FROM {source}),
b{k} AS (SELECT *, b - coalesce(sum(cap) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS l, sum(weight) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS w
        FROM a{k} WINDOW o AS ({part} ORDER BY CAST(cap AS DOUBLE) / weight, {", ".join(f"{x} NULLS FIRST" for x in names)})),
c{k} AS (SELECT *, CAST(l AS HUGEINT) * weight >= CAST(cap AS HUGEINT) * w AS full_ FROM b{k}),
g{k} AS (SELECT {cols}, tokens, CASE WHEN full_ THEN cap ELSE CAST((CAST(b AS HUGEINT) - sum(CASE WHEN full_ THEN cap ELSE 0 END) OVER ({part})) * weight // sum(CASE WHEN full_ THEN 0 ELSE weight END) OVER ({part}) AS BIGINT) END AS give FROM c{k})"""

    domain = recipe.domain_sql
    return f"""
WITH d AS (SELECT doc_id, {domain} AS domain, lang, source, CAST(coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0) AS BIGINT) AS tokens FROM documents),
leaves AS (SELECT domain, lang, source, sum(tokens) AS tokens FROM d GROUP BY ALL),{",".join(level(k) for k in range(3))},
f AS (SELECT domain AS fd, lang AS fl, source AS fs, CASE WHEN tokens > 0 THEN give // tokens ELSE 0 END AS fl_, CASE WHEN tokens > 0 THEN give % tokens ELSE 0 END AS more FROM g2),
x AS (SELECT d.*, f.fl_, f.more, md5('{recipe.seed}:' || fl_ || ':' || coalesce(CAST(doc_id AS VARCHAR), '')) AS lot FROM d JOIN f ON domain IS NOT DISTINCT FROM fd AND lang IS NOT DISTINCT FROM fl AND source IS NOT DISTINCT FROM fs),
y AS (SELECT *, sum(tokens) OVER (PARTITION BY domain, lang, source ORDER BY lot) AS run FROM x),
z AS (SELECT doc_id, domain, lang, source, tokens, CAST(fl_ + CASE WHEN more > 0 AND run <= more THEN 1 ELSE 0 END AS BIGINT) AS copies FROM y)
SELECT * FROM z WHERE copies > 0"""
