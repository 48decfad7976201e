"""SimHash near-duplicates by multi-index hashing.

Fingerprint: lower-case A-Z, split at ASCII white space, hash every 3-word shingle (repeats included;
a shorter text is one shingle) with XXH64, and set a bit where over half of the hashes have it.  A text
without words, an empty or a null text has fingerprint zero and links like any other.

Links join fingerprints that differ in at most two bits.  A fingerprint is cut into two halves; if two
differ in at most two bits, one half differs in at most one.  So each distinct fingerprint is put into a
table under both halves, and each looks up its halves and the halves with one set bit cleared (of two
halves that differ in one bit, one has it set).  Matches are verified with the complete distance.

A half shared by more than ``hot`` entries would make all pairs of them.  Its members take another exact
way: two fingerprints differ in at most two bits exactly if their balls of radius one meet, and all who
share an element of their balls are within two bits of each other, so each element links its members to
the smallest of them, in a number of rows proportional to the members.

Copies collapse to one fingerprint before anything is compared; components are found over distinct
fingerprints by alternating large and small stars, each round cut into the shared folder.

Edge cases: repeated rows each get their row; an empty table gives an empty result; a null doc_id keeps
its row and never names a component unless all ids of it are null; different texts under one doc_id are rows of their own,
in the components of their texts; extra columns of any name stay as they are.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..durable import cut
from .common import text_blocks

SHINGLE = 3
MAX_BITS = 2
HOT = 64


def fingerprint(text: bytes, shingle: int = SHINGLE) -> int:
    """Unsigned 64-bit fingerprint of one UTF-8 text."""
    words = text.lower().split()  # bytes: lowers A-Z only and splits at ASCII white space only
    if not words:
        return 0
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), 42)
    flat = b" ".join(words)
    gaps = np.flatnonzero(np.frombuffer(flat, np.uint8) == 32)
    starts = [0, *(gaps[: len(gaps) - shingle + 2] + 1).tolist()][: len(words) - shingle + 1]
    ends = [*gaps[shingle - 1 :].tolist(), len(flat)]
    digest = xxhash.xxh64_digest
    raw = np.frombuffer(b"".join([digest(flat[a:b], 42) for a, b in zip(starts, ends, strict=True)]), np.uint8).reshape(-1, 8)
    return int.from_bytes(np.packbits(2 * bit_counts(raw) > len(raw)).tobytes(), "big")


def bit_counts(raw: np.ndarray) -> np.ndarray:
    """How many rows have each bit set; bits in the order of np.unpackbits."""
    out = np.zeros(64, np.int64)
    for a in range(0, len(raw), 1 << 16):
        out += np.unpackbits(raw[a : a + (1 << 16)], axis=1).sum(axis=0, dtype=np.int64)
    return out


def fingerprints(docs: DataFrame, extra: tuple[str, ...] = ("doc_id",), shingle: int = SHINGLE) -> DataFrame:
    """``extra`` columns and ``fp`` (the fingerprint as a signed long) for each row."""
    schema = T.StructType([*(docs.schema[c] for c in extra), T.StructField("fp", T.LongType())])

    def run(batches):
        for batch in batches:
            found = np.zeros(batch.num_rows, np.uint64)
            for a, _, raw, offsets in text_blocks(batch, "text"):
                data = raw.tobytes()
                for k, (x, y) in enumerate(zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)):
                    found[a + k] = fingerprint(data[x:y], shingle)
            kept = [batch.column(batch.schema.get_field_index(c)) for c in extra]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(found.view(np.int64))], [*extra, "fp"])

    return docs.select(*extra, "text").mapInArrow(run, schema)


def _half(which: int) -> F.Column:
    return F.col("fp").bitwiseAND(F.lit(0xFFFFFFFF)) if which == 0 else F.shiftrightunsigned("fp", 32)


def _cleared(column: F.Column, bits: int) -> F.Column:
    """The values that differ from ``column`` by clearing one of its set bits."""
    flags = F.array(*[F.lit(1 << b if b < 63 else -(1 << 63)).cast("long") for b in range(bits)])
    return F.transform(F.filter(flags, lambda x: column.bitwiseAND(x) != 0), lambda x: column.bitwiseXOR(x))


def _entry(which: int, key: F.Column, own: bool = False) -> F.Column:
    return F.struct(F.lit(which).alias("seg"), key.alias("key"), F.lit(own).alias("own"))


def links(distinct: DataFrame, max_bits: int = MAX_BITS, hot: int = HOT) -> DataFrame:
    """Edges (a, b) between distinct fingerprints ``fp`` whose closure is that of all pairs within
    ``max_bits`` (at most 2)."""
    if max_bits != 2:
        raise ValueError("this index is laid out for a distance of two bits")
    base = distinct.select("fp")
    entries = base.select(
        F.explode(
            F.flatten(
                F.array(
                    *[
                        F.concat(F.array(_entry(s, _half(s), True)), F.transform(_cleared(_half(s), 32), (lambda which: lambda v: _entry(which, v))(s)))
                        for s in (0, 1)
                    ]
                )
            )
        ).alias("e"),
        "fp",
    ).select(F.col("e.seg").alias("seg"), F.col("e.key").alias("key"), F.col("e.own").alias("own"), "fp")
    # Keys that nobody owns, or that one fingerprint alone reaches, meet nothing.
    load = entries.groupBy("seg", "key").agg(F.count("*").alias("n"), F.max("own").alias("owned")).where("n > 1 and owned")
    load = cut(load)
    cold, warm = load.where(F.col("n") <= hot), load.where(F.col("n") > hot)
    met = entries.join(cold.select("seg", "key"), ["seg", "key"], "left_semi")
    left, right = met.where("own").select("seg", "key", F.col("fp").alias("a")), met.select("seg", "key", F.col("fp").alias("b"))
    near = (
        left.join(right, ["seg", "key"])
        .where((F.col("a") != F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= max_bits))
        .select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
        .distinct()
    )
    crowd = entries.join(warm.select("seg", "key"), ["seg", "key"], "left_semi").select("fp").distinct()
    every = F.array(*[F.lit(1 << b if b < 63 else -(1 << 63)).cast("long") for b in range(64)])
    balls = crowd.select("fp", F.explode(F.concat(F.array("fp"), F.transform(every, lambda x: F.col("fp").bitwiseXOR(x)))).alias("x"))
    centre = balls.groupBy("x").agg(F.min("fp").alias("a"), F.count("*").alias("n")).where("n > 1").select("x", "a")
    stars = balls.join(centre, "x").where(F.col("fp") != F.col("a")).select("a", F.col("fp").alias("b")).distinct()
    return near.union(stars).distinct()


def components(edges: DataFrame, max_rounds: int = 100) -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b); root is the smallest node of its component."""
    both = lambda e: e.select(F.col("a").alias("u"), F.col("b").alias("v")).union(e.select(F.col("b").alias("u"), F.col("a").alias("v")))
    edges = cut(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a != b").distinct())
    mark = None
    for _ in range(max_rounds):
        # Large star: larger neighbours move to the smallest neighbour.
        two = both(edges)
        low = two.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = two.join(low, "u").where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b"))
        # Small star: a node and its smaller neighbours move to the smallest of them.
        down = large.where("a > b").distinct()
        low = down.groupBy("a").agg(F.min("b").alias("m"))
        small = down.join(low, "a").where("b != m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(low.select("a", F.col("m").alias("b")))
        edges = cut(small.where("a != b").distinct())
        now = tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.xxhash64("b", "a").cast("decimal(38,0)"))).first())
        if now == mark:
            return edges.select(F.col("a").alias("node"), F.col("b").alias("root")).union(edges.select("b", "b").distinct())
        mark = now
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


def near_duplicates(docs: DataFrame, shingle: int = SHINGLE, max_bits: int = MAX_BITS, hot: int = HOT, extra: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, ``extra`` columns, fp, root (the smallest fingerprint of the component) and component_id (the smallest doc_id
    reachable over links) for each row of ``docs``."""
    marked = cut(fingerprints(docs, ("doc_id", *extra), shingle))
    distinct = cut(marked.groupBy("fp").agg(F.min("doc_id").alias("first_id")))
    roots = components(links(distinct, max_bits, hot))
    named = distinct.join(roots, distinct["fp"] == roots["node"], "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    smallest = named.groupBy("root").agg(F.min("first_id").alias("component_id"))
    ids = named.join(smallest, "root").select(F.col("fp").alias("fp_"), "root", "component_id")
    return marked.join(ids, marked["fp"] == ids["fp_"]).select("doc_id", *extra, "fp", "root", "component_id")


def report(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id."""
    return near_duplicates(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_first(docs: DataFrame) -> DataFrame:
    """One row of each component: that with the smallest doc_id, of texts under one doc_id that with the smallest hash, and
    of rows that share both that whose other columns (maps and variants aside) have the smallest hash.  Rows without a
    doc_id can't stand for others and all stay."""
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").alias("doc_id"), F.xxhash64("text").alias("h"))
    found = near_duplicates(docs.select("doc_id", F.xxhash64("text").alias("h"), "text"), extra=("h",))
    kept = found.where("doc_id is not null").groupBy("root").agg(F.min(F.struct("doc_id", "h")).alias("k")).select("k.doc_id", "k.h")
    plain = [F.col("row")[f.name] for f in docs.schema.fields if not _hides_map(f.dataType)]
    rows = keyed.join(kept, ["doc_id", "h"], "left_semi").groupBy("doc_id", "h").agg(F.min_by("row", F.xxhash64(*plain)).alias("row"))
    every = rows.select("row").union(keyed.where("doc_id is null").select("row"))
    return every.select(*[F.col("row")[c].alias(c) for c in docs.columns])


def _hides_map(kind: T.DataType) -> bool:
    return any(x in kind.simpleString() for x in ("map<", "variant"))
