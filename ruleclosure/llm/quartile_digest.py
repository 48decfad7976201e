"""Document fingerprints: quartile bucket digests.

A text's bytes are read with a sliding window of five; the six byte triplets that hold the newest byte
are hashed into 128 buckets.  Each bucket becomes two bits, by the quartile its count falls into, and
the length becomes one logarithmic byte.  The digest is 66 hex digits: 2 for the length, 64 for the buckets.

Two digests are compared by a difference score: bucket codes differ by 0 to 3 (a difference of 3 counts 6)
and length codes by their distance, beyond one step times 12.  The score is bounded by ``MAX_DIFFERENCE``; the
likeness is 1 - score / bound.

Next documents: rows are sorted over ranges, so many that each holds about ``RANGE_BYTES``; a task sees its rows in order, and its
first and last row are written with the results into the shared folder, where each last row meets the first of the next range.

Edge cases: null is the empty text; texts under five bytes have no triplets and the all-zero bucket code;
equal texts have equal digests; the next document of the last one is the first, of an only one itself;
rows are ordered by doc_id (null first) of any type that sorts, then a hash of the text, then text; an empty table gives an empty
result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..durable import cut
from .common import MASK64, blocks

BUCKETS = 128
SPAN = 5
MAX_DIFFERENCE = 300
LENGTH_STEP = 12
RANGE_BYTES = 64_000_000

#: Offsets back from the newest byte, two for each of the six triplets.
_PAIRS = list(itertools.combinations(range(1, SPAN), 2))


def _byte_tables() -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Three seeded random byte tables for each triplet (splitmix64, top bits)."""
    state, out = 0x1234567, []
    def draw():
        nonlocal state
        state = (state + 0x9E3779B97F4A7C15) & MASK64
        z = state
        z = ((z ^ (z >> 30)) * 0xBF58476D1CE4E5B9) & MASK64
        z = ((z ^ (z >> 27)) * 0x94D049BB133111EB) & MASK64
        return (z ^ (z >> 31)) >> 57
    for _ in _PAIRS:
        out.append(tuple(np.array([draw() for _ in range(256)], np.uint8) for _ in range(3)))
    return out


_TABLES = _byte_tables()


def bucket_counts(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """(texts, BUCKETS) counts of hashed triplets."""
    m, n = len(offsets) - 1, len(raw)
    out = np.zeros(m * BUCKETS, np.int64)
    if n >= SPAN:
        row = np.repeat(np.arange(m, dtype=np.int64), np.diff(offsets))
        ok = row[SPAN - 1 :] == row[: n - SPAN + 1]
        base = row[SPAN - 1 :][ok] * BUCKETS
        for (i, j), (t0, t1, t2) in zip(_PAIRS, _TABLES, strict=True):
            h = t0[raw[SPAN - 1 :]] ^ t1[raw[SPAN - 1 - i : n - i]] ^ t2[raw[SPAN - 1 - j : n - j]]
            out += np.bincount(base + h[ok], minlength=m * BUCKETS)
    return out.reshape(m, BUCKETS)


def length_code(n: np.ndarray) -> np.ndarray:
    """Steps of a fifth of a power of e, so that a code covers lengths within about 22 percent."""
    return np.minimum(255, np.floor(5 * np.log1p(np.asarray(n, np.float64)))).astype(np.uint8)


def digests(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """(texts, 1 + BUCKETS) codes: length, then 0 to 3 for each bucket."""
    counts = bucket_counts(raw, offsets)
    ranked = np.sort(counts, axis=1)
    q = [ranked[:, BUCKETS * k // 4 - 1][:, None] for k in (1, 2, 3)]
    codes = (counts > q[0]).astype(np.uint8) + (counts > q[1]) + (counts > q[2])
    return np.concatenate([length_code(np.diff(offsets))[:, None], codes], axis=1).astype(np.uint8)


def packed(codes: np.ndarray) -> list[str]:
    c = codes[:, 1:].reshape(len(codes), BUCKETS // 4, 4)
    packed_bytes = (c[..., 0] << 6) | (c[..., 1] << 4) | (c[..., 2] << 2) | c[..., 3]
    return [bytes([n, *row]).hex() for n, row in zip(codes[:, 0].tolist(), packed_bytes.tolist(), strict=True)]


def difference(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Bounded difference score of digest codes, row by row."""
    step = np.abs(a[:, 1:].astype(np.int64) - b[:, 1:])
    body = np.where(step == 3, 6, step).sum(axis=1)
    far = np.abs(a[:, 0].astype(np.int64) - b[:, 0])
    return np.minimum(MAX_DIFFERENCE, body + np.where(far <= 1, far, LENGTH_STEP * far))


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return 1.0 - difference(a, b) / MAX_DIFFERENCE


def _of_texts(texts: list[bytes]) -> np.ndarray:
    sizes = np.array([0, *map(len, texts)], np.int64)
    offsets, data = np.cumsum(sizes), np.frombuffer(b"".join(texts), np.uint8)
    out = [digests(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in blocks(offsets)]
    return np.concatenate(out) if out else np.zeros((0, BUCKETS + 1), np.uint8)


def fingerprint(text: str | None) -> str:
    return packed(_of_texts([(text or "").encode()]))[0]


def edited(text: str, following: str) -> str:
    """The last floor(n/2) code points replaced by the first as many (or all) of the following text."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def ordered(docs: DataFrame, ranges: int | None = None) -> DataFrame:
    """doc_id, text: sorted over ranges."""
    base = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("h", F.xxhash64("text"))
    n = ranges or 1 + (docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // RANGE_BYTES
    n = max(n, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))) if ranges is None else n
    # Ranges are drawn from a sample of short keys; chance parts only rows that are the same.
    dealt = base.withColumn("chance", F.rand(3)).repartitionByRange(n, F.asc_nulls_first("doc_id"), "h", "chance")
    return dealt.sortWithinPartitions(F.asc_nulls_first("doc_id"), "h", "text").select("doc_id", "text")


NAMES = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]


def judged(rows: list[tuple], id_type: pa.DataType) -> list[pa.Array]:
    """The columns ``NAMES`` for rows (doc_id, text) in order; the last one only follows."""
    texts = [t for _, t in rows]
    raw = [t.encode() for t in texts]
    changed = [edited(t, u).encode() for t, u in itertools.pairwise(texts)]
    own, other = _of_texts(raw), _of_texts(changed)
    return [
        pa.array([i for i, _ in rows[:-1]], id_type),
        pa.array([len(t) for t in texts[:-1]], pa.int64()),
        pa.array([hashlib.sha256(x).hexdigest() for x in changed], pa.string()),
        pa.array(packed(own[:-1]), pa.string()),
        pa.array(packed(other), pa.string()),
        pa.array(likeness(own[:-1], other)),
        pa.array(likeness(own[:-1], own[1:])),
    ]


def report(docs: DataFrame, ranges: int | None = None) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    kinds = [T.LongType(), T.StringType(), T.StringType(), T.StringType(), T.DoubleType(), T.DoubleType()]
    schema = T.StructType([docs.schema["doc_id"], *(T.StructField(n, k) for n, k in zip(NAMES[1:], kinds, strict=True))])
    edges = T.StructType([*schema.fields, T.StructField("edge", T.StringType()), T.StructField("place", T.IntegerType()), T.StructField("text", T.StringType())])

    def run(batches):
        import pyspark

        place, first, held, held_bytes, id_type = pyspark.TaskContext.get().partitionId(), None, [], 0, None

        def out(rows):
            found = judged(rows, id_type)
            n = len(found[0])
            return pa.RecordBatch.from_arrays([*found, pa.nulls(n, pa.string()), pa.nulls(n, pa.int32()), pa.nulls(n, pa.string())], edges.fieldNames())

        for batch in batches:
            id_type = batch.schema.field("doc_id").type
            for row in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                first = first or row
                held.append(row)
                held_bytes += len(row[1])
                if len(held) > 1 and held_bytes > 1_000_000:
                    yield out(held)
                    held, held_bytes = held[-1:], len(row[1])
        if len(held) > 1:
            yield out(held)
        if held:
            rest = [pa.nulls(2, t) for t in (pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64())]
            ends = [first, held[-1]]
            named = [pa.array(["first", "last"]), pa.array([place] * 2, pa.int32()), pa.array([t for _, t in ends], pa.string())]
            yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in ends], id_type), *rest, *named], edges.fieldNames())

    def close(batches):
        for batch in batches:
            id_type = batch.schema.field("doc_id").type
            for i, t, u in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                yield pa.RecordBatch.from_arrays(judged([(i, t), (None, u)], id_type), NAMES)

    found = cut(ordered(docs, ranges).mapInArrow(run, edges))
    # Ranges with rows, a number each; the numbers alone say which follows which.
    places = sorted(r[0] for r in found.where("edge = 'first'").select("place").collect())
    follows = docs.sparkSession.createDataFrame(list(zip(places, [*places[1:], *places[:1]], strict=True)), "at int, following int")
    last = found.where("edge = 'last'").select("doc_id", "text", "place").join(follows, F.col("place") == F.col("at"))
    first = found.where("edge = 'first'").select(F.col("text").alias("next_text"), F.col("place").alias("next_place"))
    met = last.join(first, F.col("following") == F.col("next_place")).select("doc_id", "text", "next_text")
    return found.where("edge is null").select(NAMES).union(met.mapInArrow(close, schema))
