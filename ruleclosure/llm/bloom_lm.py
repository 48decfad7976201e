"""Language-model scores from a log-frequency Bloom filter.

Tokens are lower-cased (A-Z) words between ASCII white space, then one end mark per text.  A count c is
quantised to q = 1 + floor(log_b c), and the filter holds the pairs (n-gram, 1) .. (n-gram, q); a count is read back
by probing 1, 2, ... until a probe misses, and stands for the middle of its range.  The filter keeps 1- and
2-grams; a token's probability mixes its share among followers of the token before it with its own share:

    P(w | v) = m(v) * c(v w) / c(v) + (1 - m(v)) * (c(w) + 0.1) / (N + 0.1 (V + 1)),   m(v) = MIX * c(v) / (c(v) + HALF)

The filter grows with the corpus, so it is never in one place.  It is a row of segments, each sized for its own entries:

1. Texts are put into blocks of at most ``BLOCK`` bytes (or one text) with a number each, cut compressed into the shared folder.
2. A block sends its distinct n-grams, with how often its training texts hold them, to the ``lots`` that own them (top bits of
   the hash).  A lot adds up the counts, builds its segment, probes it for every n-gram it was asked for, and answers
   block by block: a level a 2-gram, a level and the exact count a 1-gram.
3. Answers meet their blocks, which are read once more and scored.

So work is linear in the corpus and n-grams travel once.  The segments of 1-grams together are broadcast to the workers and probed
there where they hold at most ``max_filter_bytes``; where they outgrow it, the levels in the answers serve.

Beside the model stands the exact base score, from the exact counts of 1-grams.  Words are told apart by 64-bit hashes.

Edge cases: null is the empty text, which holds the end mark alone; repeated rows count each time in training
and each get their row; with no training text every count is 0 and all scores are those of the smoothing
term; a null doc_id hashes as the empty string; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..durable import cut
from .common import MASK64, Spans, lower_table, mix, opened, sent, text_blocks

LOG_BASE = 1.5
BITS, PROBES = 10, 4
#: Bytes of text in a block; a larger block repeats more of its n-grams.
BLOCK = 2_500_000
#: Distinct n-grams of blocks that a lot takes on average.
LOT_GRAMS = 1 << 18
MIX, HALF = 0.3, 20.0
MAX_FILTER_BYTES = 64_000_000
END = np.uint64(0x2545F4914F6CDD1D)

_LOWER = lower_table()
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_STEP, _TURN = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)


def token_hashes(raw: np.ndarray, offsets: np.ndarray):
    """(hash of each token, text by text with end marks, index of its text, hash of the token before it)."""
    m, n = len(offsets) - 1, len(raw)
    if n:
        low = _LOWER[raw]
        word = ~_SPACE[low]
        edge = np.zeros(n + 1, bool)
        edge[offsets] = True
        starts = np.flatnonzero(word & (edge[:-1] | np.concatenate([[True], ~word[:-1]])))
        ends = np.flatnonzero(word & (edge[1:] | np.concatenate([~word[1:], [True]]))) + 1
        row = np.searchsorted(offsets, starts, side="right") - 1
        hashes = Spans(low).hash(starts, ends)
    else:
        row, hashes = np.zeros(0, np.int64), np.zeros(0, np.uint64)
    sizes = np.bincount(row, minlength=m) + 1
    out = np.full(len(hashes) + m, END, np.uint64)
    out[np.arange(len(hashes)) + row] = hashes
    doc = np.repeat(np.arange(m), sizes)
    before = np.empty_like(out)
    before[:1], before[1:] = END, out[:-1]
    before[np.cumsum(sizes)[:-1]] = END
    return out, doc, before


def pair_hash(before: np.ndarray, token: np.ndarray) -> np.ndarray:
    return mix(before * _STEP + (token ^ (token >> np.uint64(29))))


def quantised(counts: np.ndarray) -> np.ndarray:
    return 1 + np.floor(np.log(counts) / np.log(LOG_BASE) + 1e-9).astype(np.int64)


def restored(q: np.ndarray) -> np.ndarray:
    """The middle of the counts that share a level; 0 for level 0, and exact while a level holds one count."""
    low = np.ceil(LOG_BASE ** (q - 1.0) - 1e-9)
    high = np.maximum(low, np.ceil(LOG_BASE ** np.asarray(q, float) - 1e-9) - 1)
    return np.where(q > 0, (low + high) / 2, 0.0)


def positions(h: np.ndarray, level, size, probe: int) -> np.ndarray:
    turn = np.uint64((int(level) * int(_STEP) + probe * int(_TURN)) & MASK64) if np.ndim(level) == 0 else level.astype(np.uint64) * _STEP + np.uint64(probe * int(_TURN) & MASK64)
    return (mix(h + turn) % np.asarray(size).astype(np.uint64)).astype(np.int64)


def build_segment(h: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The bits, packed, of one segment."""
    q = quantised(counts)
    keys, total = np.repeat(h, q), int(q.sum())
    level = np.arange(total) - np.repeat(np.cumsum(q) - q, q) + 1
    size = -(-total * BITS // 8) * 8
    bits = np.zeros(size, bool)
    for probe in range(PROBES):
        bits[positions(keys, level, size, probe)] = True
    return np.packbits(bits, bitorder="little")


class Filter:
    """Segments side by side; ``first`` and ``size`` in bits by number (size 0: nothing there).  The number is the top bits
    of the hash."""

    def __init__(self, segments: dict[int, bytes], lot_bits: int):
        self.lot_bits = lot_bits
        self.size = np.zeros(1 << lot_bits, np.int64)
        for k, x in segments.items():
            self.size[k] = 8 * len(x)
        self.first = np.cumsum(self.size) - self.size
        self.data = np.frombuffer(b"".join(segments[k] for k in sorted(segments)), np.uint8)

    def levels(self, h: np.ndarray) -> np.ndarray:
        """Level of each n-gram; 0 where the first probe misses."""
        lot = lot_of(h, self.lot_bits)
        first, size = self.first[lot], self.size[lot]
        out, alive = np.zeros(len(h), np.uint8), np.flatnonzero(size)
        level = 1
        while len(alive):
            for probe in range(PROBES):
                at = first[alive] + positions(h[alive], level, size[alive], probe)
                alive = alive[(self.data[at >> 3] >> (at & 7)) & 1 == 1]
                if not len(alive):
                    break
            out[alive] = level
            level += 1
        return out


def lot_of(h: np.ndarray, lot_bits: int) -> np.ndarray:
    return (h >> np.uint64(64 - lot_bits)).astype(np.int64)


def lot_bits_for(docs: DataFrame) -> int:
    """So many lots of each order that each has about ``LOT_GRAMS`` n-grams; at least two."""
    size = docs.agg(F.sum(F.octet_length("text") + F.lit(6))).first()[0] or 0
    return min(24, max(1, int(size // 6 // LOT_GRAMS).bit_length()))


def blocked(docs: DataFrame, training: F.Column) -> DataFrame:
    """blk, z (the texts of a block, compressed), sizes, ids, learn."""
    schema = T.StructType(
        [
            T.StructField("z", T.BinaryType()),
            T.StructField("sizes", T.ArrayType(T.IntegerType())),
            T.StructField("ids", T.ArrayType(docs.schema["doc_id"].dataType)),
            T.StructField("learn", T.ArrayType(T.BooleanType())),
        ]
    )

    def run(batches):
        press = zstandard.ZstdCompressor(level=1)
        for batch in batches:
            for a, b, raw, offsets in text_blocks(batch, "text", BLOCK):
                ends = pa.array([0, b - a], pa.int32())
                lists = [pa.ListArray.from_arrays(ends, x) for x in (pa.array(np.diff(offsets).astype(np.int32)), batch.column(0).slice(a, b - a), batch.column(2).slice(a, b - a))]
                yield pa.RecordBatch.from_arrays([pa.array([press.compress(raw.tobytes())], pa.binary()), *lists], schema.fieldNames())

    rows = docs.select("doc_id", "text", F.coalesce(training, F.lit(False)).alias("learn")).mapInArrow(run, schema)
    return rows.withColumn("blk", F.monotonically_increasing_id())


def _texts(z: bytes, sizes: list[int]) -> tuple[np.ndarray, np.ndarray]:
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(z), np.uint8)
    return raw, np.concatenate([[0], np.cumsum(np.asarray(sizes, np.int64))])


def narrow(values: np.ndarray) -> bytes:
    """Counts in as few bytes each as the largest takes, that number first."""
    width = next(w for w in (1, 2, 4, 8) if w == 8 or values.max(initial=0) < 1 << 8 * w)
    return bytes([width]) + values.astype(f"<u{width}").tobytes()


def wide(cell: bytes) -> np.ndarray:
    return np.frombuffer(cell, f"<u{cell[0]}", offset=1).astype(np.int64)


def asked(blocks: DataFrame, lot_bits: int) -> DataFrame:
    """lot, blk, h, n: the distinct n-grams of each block in order, by lot, and how often its training texts hold each."""

    def run(batches):
        for batch in batches:
            for k in range(batch.num_rows):
                blk, z, sizes, learn = (batch.column(c)[k].as_py() for c in range(4))
                token, doc, before = token_hashes(*_texts(z, sizes))
                weight = np.array(learn, np.float64)[doc]
                out = [[], [], []]
                for order, grams in ((0, token), (1, pair_hash(before, token))):
                    h, back = np.unique(grams, return_inverse=True)
                    n = np.bincount(back, weight, len(h)).astype(np.int32)
                    lot = lot_of(h, lot_bits)
                    cuts = [0, *(np.flatnonzero(np.diff(lot)) + 1).tolist(), len(lot)]
                    out[0] += (lot[cuts[:-1]] + (order << lot_bits)).tolist()
                    for values, cells, pack in ((h, out[1], np.ndarray.tobytes), (n, out[2], narrow)):
                        cells += [pack(values[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(out[0], pa.int32()), pa.array([blk] * len(out[0]), pa.int64()), pa.array(out[1], pa.binary()), pa.array(out[2], pa.binary())], ["lot", "blk", "h", "n"]
                )

    return blocks.select("blk", "z", "sizes", "learn").mapInArrow(run, "lot int, blk long, h binary, n binary")


def answered(grams: DataFrame, lot_bits: int) -> DataFrame:
    """blk, lot, levels, counts (of 1-grams only); and, with null blk, one row for each lot: the bits of its segment (of 1-grams
    only), the sum of its counts and how many n-grams have one."""
    schema = "blk long, lot int, levels binary, counts binary, bits binary, total long, distinct long"
    names = ["blk", "lot", "levels", "counts", "bits", "total", "distinct"]
    one = 1 << lot_bits

    def finish(lot, blks, hs, ns):
        h, back = np.unique(np.concatenate(hs), return_inverse=True)
        counts = np.bincount(back, np.concatenate(ns), len(h)).astype(np.int64)
        known = counts > 0
        segment = build_segment(h[known], counts[known]).tobytes() if known.any() else b""
        levels = Filter({lot % one: segment} if segment else {}, lot_bits).levels(h)[back]
        exact, m = counts[back], len(blks)
        ends = np.cumsum([len(x) for x in hs]).tolist()
        cells = lambda values, pack: [pack(values[a:b]) for a, b in zip([0, *ends[:-1]], ends, strict=True)]
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([*blks, None], pa.int64()), pa.array([lot] * (m + 1), pa.int32()), pa.array([*cells(levels, np.ndarray.tobytes), None], pa.binary()),
                pa.array([*(cells(exact, narrow) if lot < one else [None] * m), None], pa.binary()), pa.array([*[None] * m, segment if lot < one else None], pa.binary()),
                pa.array([*[None] * m, int(counts.sum())], pa.int64()), pa.array([*[None] * m, int(known.sum())], pa.int64()),
            ],
            names,
        )

    def run(batches):
        at, held = None, ([], [], [])
        for batch in batches:
            for lot, blk, h, n in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                if lot != at:
                    if held[0]:
                        yield from finish(at, *held)
                    at, held = lot, ([], [], [])
                for out, x in zip(held, (blk, np.frombuffer(h, np.uint64), wide(n)), strict=True):
                    out.append(x)
        if held[0]:
            yield from finish(at, *held)

    return grams.repartition("lot").sortWithinPartitions("lot").mapInArrow(run, schema)


class Smoothing:
    """N and V of the training texts, and the broadcast filter of 1-grams (None: levels come with the answers)."""

    def __init__(self, total: int, distinct: int, ones: Filter | None):
        self.total, self.distinct, self.ones = total, distinct, ones and vars(ones)

    def filter(self) -> Filter | None:
        if self.ones is None:
            return None
        out = Filter.__new__(Filter)
        out.__dict__.update(self.ones)
        return out


def scored(raw: np.ndarray, offsets: np.ndarray, levels: list[np.ndarray], counts: np.ndarray, s: Smoothing, ones: Filter | None):
    """Per text: tokens, known tokens, base score, model score.  levels: of the block's distinct 1- and 2-grams in order; counts: of its 1-grams."""
    m = len(offsets) - 1
    token, doc, before = token_hashes(raw, offsets)
    words, back = np.unique(token, return_inverse=True)
    grams, gram_back = np.unique(pair_hash(before, token), return_inverse=True)
    scale = s.total + 0.1 * (s.distinct + 1)
    known = np.bincount(doc, counts[back] > 0, m).astype(np.int64)
    base = np.bincount(doc, np.log10((counts + 0.1) / scale)[back], m)
    c_word = restored(levels[0] if ones is None else ones.levels(words))[back]
    together = restored(levels[1])[gram_back]
    # A text's first token follows an end mark, which counts as much as the text's own.
    last = np.cumsum(np.bincount(doc, minlength=m)) - 1
    c_before = np.roll(c_word, 1)
    c_before[np.append(0, last[:-1] + 1)] = c_word[last]
    share = MIX * c_before / (c_before + HALF)
    p = share * np.minimum(together, c_before) / np.maximum(c_before, 1) + (1 - share) * (c_word + 0.1) / scale
    return np.bincount(doc, minlength=m), known, base, np.bincount(doc, np.log10(np.minimum(p, 1.0)), m)


def score(docs: DataFrame, training: F.Column, max_filter_bytes: int = MAX_FILTER_BYTES) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score for each row of ``docs``."""
    lot_bits = lot_bits_for(docs)
    one = 1 << lot_bits
    blocks = cut(blocked(docs, training))
    answers = cut(answered(asked(blocks, lot_bits), lot_bits))
    lots = answers.where(f"blk is null and lot < {one}")
    n, v, size = lots.agg(F.coalesce(F.sum("total"), F.lit(0)), F.coalesce(F.sum("distinct"), F.lit(0)), F.coalesce(F.sum(F.length("bits")), F.lit(0))).first()
    ones = None
    if size <= max_filter_bytes:
        found = lots.where("length(bits) > 0").select("lot", "bits").toArrow()
        ones = Filter(dict(zip(found.column(0).to_pylist(), found.column(1).to_pylist(), strict=True)), lot_bits)
    shared = sent(docs, Smoothing(n, v, ones))
    id_field = docs.schema["doc_id"]
    schema = T.StructType(
        [id_field, *(T.StructField(x, T.LongType()) for x in ("n_tokens", "n_known", "train_tokens")), *(T.StructField(x, T.DoubleType()) for x in ("base_score", "score"))]
    )
    nothing = F.lit(None)
    texts = blocks.select("blk", F.lit(-1).alias("lot"), "z", "sizes", "ids", nothing.cast("binary").alias("levels"), nothing.cast("binary").alias("counts"))
    marks = answers.where("blk is not null").select("blk", "lot", nothing.cast("binary").alias("z"), *(nothing.cast(blocks.schema[c].dataType).alias(c) for c in ("sizes", "ids")), "levels", "counts")

    def run(batches):
        s = opened(Smoothing, shared)
        ones, block, levels, counts = s.filter(), None, ([], []), []

        def finish():
            z, sizes, ids = block
            kinds = [np.frombuffer(b"".join(x), np.uint8) for x in levels]
            found = scored(*_texts(z, sizes), kinds, np.concatenate([wide(x) for x in counts]), s, ones)
            total = pa.array(np.full(len(ids), s.total, np.int64))
            return pa.RecordBatch.from_arrays([ids, *(pa.array(x) for x in found[:2]), total, *(pa.array(x) for x in found[2:])], schema.fieldNames())

        for batch in batches:
            lot, z, sizes, marked, exact = (batch.column(k) for k in (1, 2, 3, 5, 6))
            for k, number in enumerate(lot.to_pylist()):
                if number < 0:
                    if block:
                        yield finish()
                    block, levels, counts = (z[k].as_py(), sizes[k].as_py(), batch.column(4)[k].values), ([], []), []
                else:
                    levels[number >= one].append(marked[k].as_py())
                    if number < one:
                        counts.append(exact[k].as_py())
        if block:
            yield finish()

    return texts.union(marks).repartition("blk").sortWithinPartitions("blk", "lot").mapInArrow(run, schema)


def held_out(modulus: int = 10, rest: int = 0) -> F.Column:
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(modulus)) == rest


def report(docs: DataFrame, max_filter_bytes: int = MAX_FILTER_BYTES) -> DataFrame:
    """The scores, learning from the rows that are not held out; ``held_out`` tells which are."""
    found = score(docs, ~held_out(), max_filter_bytes)
    return found.select("doc_id", held_out().alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")
