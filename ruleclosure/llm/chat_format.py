"""Chat formatting with cumulative-snapshot collapse.

Loggers often store a conversation again after each turn, so one conversation prefixes another.  Every turn
prefix gets a rolling hash: the exclusive or, over its turns, of hashes bound to position, role and text (two
independent 64-bit hashes).  A conversation whose whole hash occurs as a proper prefix of a longer one is dropped
by an anti-join; of equal conversations that with the smallest conv_id stays.  What remains is rendered in
chunks of at most ``CHUNK`` turns, which joined in order are the conversation.

Rows are sorted by conversation and turn over ranges, so a long conversation lies in several of them: rows are numbered and
hashed within a range (``block``), and block totals, far fewer, are summed over the conversation.  A long conversation, or many
turns with one number or none, thus spread over tasks; only turns alike in number, role and their first ``SEEN`` characters meet.

Edge cases: turns with a null conv_id belong to no conversation and are left out; turns are ordered by turn
(null first), role, text; repeated rows are turns of their own; null role or text renders as empty and is
told apart from the empty string only in order; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from ..durable import cut

CHUNK = 64
#: Characters of role and text by which equal turn numbers are spread.
SEEN = 128
OPEN, BETWEEN, CLOSE = "<|", "|>\n", "\n<|end|>\n"


def rendered(role: F.Column, text: F.Column) -> F.Column:
    """One turn."""
    return F.concat(F.lit(OPEN), F.coalesce(role, F.lit("")), F.lit(BETWEEN), F.coalesce(text, F.lit("")), F.lit(CLOSE))


def _running(df: DataFrame, inside: W.WindowSpec, value: dict[str, F.Column], total: dict[str, F.Column], carry) -> DataFrame:
    """Running aggregates over a conversation: within a block by window, between blocks from block totals."""
    order = W.Window.partitionBy("conv_id").orderBy("block").rowsBetween(W.Window.unboundedPreceding, -1)
    blocks = df.groupBy("conv_id", "block").agg(*[t.alias(f"{k}_t") for k, t in total.items()])
    before = blocks.select("conv_id", "block", *[F.coalesce(carry(f"{k}_t").over(order), F.lit(0)).alias(f"{k}_b") for k in total])
    return df.select("*", *[v.over(inside).alias(f"{k}_i") for k, v in value.items()]).join(before, ["conv_id", "block"])


def prefixes(conversations: DataFrame) -> DataFrame:
    """conv_id, pos, role, text, h1, h2: hashes of the first ``pos`` turns."""
    rows = conversations.where("conv_id is not null").select("conv_id", "turn", "role", "text")
    order = [F.asc_nulls_first(c) for c in ("turn", "role", "text")]
    # Ranges are drawn from a sample of keys that reaches the driver, so these hold begins of texts only.
    near = [F.asc("conv_id"), F.asc_nulls_first("turn"), *[F.asc_nulls_first(F.substring(c, 1, SEEN)) for c in ("role", "text")]]
    rows = cut(rows.repartitionByRange(*near).withColumn("block", F.spark_partition_id()))
    inside = W.Window.partitionBy("conv_id", "block").orderBy(*order).rowsBetween(W.Window.unboundedPreceding, 0)
    numbered = _running(rows, inside, {"n": F.count("*")}, {"n": F.count("*")}, F.sum).withColumn("pos", F.col("n_i") + F.col("n_b"))
    role, text = F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))
    bound = numbered.select("conv_id", "block", "pos", "role", "text", F.xxhash64(F.lit(1), "pos", role, text).alias("a"), F.xxhash64(F.lit("second"), text, "pos", role).alias("b"))
    by_place = W.Window.partitionBy("conv_id", "block").orderBy("pos").rowsBetween(W.Window.unboundedPreceding, 0)
    mixed = {"x": F.bit_xor("a"), "y": F.bit_xor("b")}
    both = _running(bound, by_place, mixed, mixed, F.bit_xor)
    return both.select("conv_id", "pos", "role", "text", F.col("x_i").bitwiseXOR(F.col("x_b")).alias("h1"), F.col("y_i").bitwiseXOR(F.col("y_b")).alias("h2"))


def maximal(prefix: DataFrame) -> DataFrame:
    """conv_id and n_turns of the conversations that prefix no longer one; of equal ones the first."""
    whole = prefix.groupBy("conv_id").agg(F.max("pos").alias("n_turns"), F.max_by(F.struct("h1", "h2"), "pos").alias("w"))
    whole = whole.select("conv_id", "n_turns", "w.h1", "w.h2")
    first = whole.groupBy("n_turns", "h1", "h2").agg(F.min("conv_id").alias("conv_id"))
    sizes = whole.select("conv_id", "n_turns")
    proper = prefix.select("conv_id", "pos", "h1", "h2").join(sizes, "conv_id").where("pos < n_turns").select(F.col("pos").alias("n_turns"), "h1", "h2").distinct()
    return first.join(proper, ["n_turns", "h1", "h2"], "left_anti").select("conv_id", "n_turns")


def render(conversations: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """conv_id, n_turns, chunk (from 0), rendered."""
    prefix = cut(prefixes(conversations))
    kept = prefix.join(maximal(prefix), "conv_id")
    place = F.floor((F.col("pos") - 1) / chunk).alias("chunk")
    parts = kept.groupBy("conv_id", "n_turns", place).agg(F.sort_array(F.collect_list(F.struct("pos", rendered(F.col("role"), F.col("text")).alias("r")))).alias("t"))
    return parts.select("conv_id", "n_turns", "chunk", F.array_join(F.transform("t", lambda x: x["r"]), "").alias("rendered"))


SQL = f"""
WITH t AS (SELECT conv_id, coalesce(role, '') AS role, coalesce(text, '') AS text,
                  row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS pos
           FROM conversations WHERE conv_id IS NOT NULL),
p AS (SELECT *, string_agg(md5(role || chr(1) || text), '') OVER (PARTITION BY conv_id ORDER BY pos) AS h, count(*) OVER (PARTITION BY conv_id) AS n_turns FROM t),
w AS (SELECT conv_id, n_turns, h FROM p WHERE pos = n_turns),
k AS (SELECT n_turns, h, min(conv_id) AS conv_id FROM w GROUP BY ALL),
m AS (SELECT conv_id, n_turns FROM k WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.h = k.h AND p.pos < p.n_turns))
SELECT p.conv_id, p.n_turns, (p.pos - 1) // {CHUNK} AS chunk,
       string_agg('{OPEN}' || role || '|>' || chr(10) || text || chr(10) || '<|end|>' || chr(10), '' ORDER BY pos) AS rendered
FROM p JOIN m ON p.conv_id = m.conv_id GROUP BY ALL"""
