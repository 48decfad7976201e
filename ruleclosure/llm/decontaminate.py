"""Benchmark decontamination: a broadcast hash set of normalised test n-grams.

Words are maximal runs of ASCII letters and digits and of all non-ASCII characters, after lower-casing
A-Z.  A *window* is 13 consecutive words of a benchmark item (an item of 1 to 12 words is one window).
Workers hash the windows of a text with prefix sums, look the hashes up in the sorted set, verify each
hit against the bytes of the benchmark, and mark the words inside.

The set is flat arrays: sorted hashes, where each window lies in the normalised benchmark, and its items.  A benchmark of more
than ``part_bytes`` is split by item into parts, each broadcast alone; the texts then pass the parts one after another,
cut into the shared folder in between, and keep what they have gathered.

Edge cases: a null or empty text has no words and is never contaminated; items without words never
match; repeated documents and items are each judged alone (items with one id count once); items with a
null id mark words but are not listed; extra columns of any name are kept or ignored; an empty benchmark leaves everything clean.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..durable import cut
from .common import BASE_B, Spans, buffers, free_name, lower_table, opened, sent, text_blocks

WINDOW = 13
#: Benchmark text in one broadcast set; the set takes about six times as much memory.
PART_BYTES = 24_000_000
MAP_BITS = 20
#: Bytes of text that a worker looks at together.
BLOCK = 1_000_000

_LOWER = lower_table()
_WORD = np.zeros(256, bool)
_WORD[48:58] = _WORD[97:123] = True
_WORD[128:] = True


def words_of(raw: np.ndarray, offsets: np.ndarray):
    """(lower-cased bytes, word starts, word ends, row of each word)."""
    low = _LOWER[raw]
    n = len(low)
    if n == 0:
        none = np.zeros(0, np.int64)
        return low, none, none, none
    word = _WORD[low]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    before = np.empty(n, bool)
    before[0], before[1:] = False, word[:-1]
    after = np.empty(n, bool)
    after[-1], after[:-1] = False, word[1:]
    starts = np.flatnonzero(word & (~before | edge[:-1]))
    ends = np.flatnonzero(word & (~after | edge[1:])) + 1
    return low, starts, ends, np.searchsorted(offsets, starts, side="right") - 1


def normalised(low: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The words with one space between, and where each starts there (one more: the end, a space too far)."""
    sizes = ends - starts + 1
    at = np.concatenate([[0], np.cumsum(sizes)])
    out = np.full(int(at[-1]), 32, np.uint8)
    inside = np.ones(len(out), bool)
    inside[at[1:] - 1] = False
    change = np.zeros(len(low) + 1, np.int8)
    change[starts] = 1
    change[ends] -= 1
    out[inside] = low[np.cumsum(change[:-1], dtype=np.int8).astype(bool)] if len(low) else low
    return out, at


class WindowSet:
    """Windows of items.  Per size of window: sorted hashes, begin and end of each window in ``text``, and a range of
    ``owners`` (item numbers)."""

    def __init__(self, texts: pa.Array, window: int = WINDOW):
        raw, offsets = buffers(texts)
        low, starts, ends, item = words_of(raw, offsets)
        self.text, at = normalised(low, starts, ends)
        sums = Spans(Spans(low).hash(starts, ends), BASE_B)
        del low, raw
        words = np.bincount(item, minlength=len(offsets) - 1)
        size_of = np.minimum(words, window)[item]
        left = np.cumsum(words)[item] - np.arange(len(item)) if len(item) else item  # words from here to the item's end
        self.by_size = []
        for size in np.unique(size_of).tolist():
            first = np.flatnonzero((size_of == size) & (left >= size))
            h = sums.hash(first, first + size)
            order = np.argsort(h, kind="stable")
            first, h = first[order], h[order]
            # One entry for each different window; equal hashes of different bytes stay apart.
            same = np.concatenate([[False], h[1:] == h[:-1]])
            for k in np.flatnonzero(same).tolist():
                same[k] = self._bytes(at, first[k], size) == self._bytes(at, first[k - 1], size)
            entry = np.cumsum(~same) - 1
            pairs = np.unique(np.stack([entry, item[first]]), axis=1)
            head = np.flatnonzero(~same)
            seen = np.zeros(1 << MAP_BITS, bool)  # answers most probes without a binary search
            seen[(h[head] >> np.uint64(64 - MAP_BITS)).astype(np.int64)] = True
            begin, end = at[first[head]], at[first[head] + size] - 1
            self.by_size.append((size, h[head], begin, end, np.searchsorted(pairs[0], np.arange(len(head) + 1)), pairs[1].astype(np.int32), seen))

    def _bytes(self, at: np.ndarray, k: int, size: int) -> bytes:
        return self.text[at[k] : at[k + size] - 1].tobytes()


def scan_block(raw: np.ndarray, offsets: np.ndarray, windows: WindowSet):
    """(words, starts, ends, row of word, hit flag of word, numbers of the items met by row)."""
    low, starts, ends, row = words_of(raw, offsets)
    n = len(starts)
    change = np.zeros(n + 1, np.int32)
    items: dict[int, set] = defaultdict(set)
    if n:
        text, at = None, None
        sums = Spans(Spans(low).hash(starts, ends), BASE_B)
        for size, hashes, begin, end, first_owner, owners, seen in windows.by_size:
            if n < size:
                continue
            first = np.arange(n - size + 1)
            h = sums.hash(first, first + size)
            able = seen[(h >> np.uint64(64 - MAP_BITS)).astype(np.int64)] & (row[: n - size + 1] == row[size - 1 :])
            met = np.flatnonzero(able)
            near = np.searchsorted(hashes, h[met])
            good = hashes[np.minimum(near, len(hashes) - 1)] == h[met]
            for k, j in zip(met[good].tolist(), near[good].tolist(), strict=True):
                if text is None:
                    text, at = normalised(low, starts, ends)
                mine = text[at[k] : at[k + size] - 1].tobytes()
                while j < len(hashes) and hashes[j] == h[k]:
                    # Equal hashes are not enough: the words must be equal.
                    if windows.text[begin[j] : end[j]].tobytes() == mine:
                        change[k] += 1
                        change[k + size] -= 1
                        items[int(row[k])].update(owners[first_owner[j] : first_owner[j + 1]].tolist())
                    j += 1
    return starts, ends, row, np.cumsum(change[:-1]) > 0, items


def parts_of(benchmark: DataFrame, part_bytes: int = PART_BYTES) -> list[DataFrame]:
    """item_id and text in parts of about ``part_bytes``, dealt by a hash of the text."""
    items = benchmark.select("item_id", F.coalesce("text", F.lit("")).alias("text"))
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(1, -(-size // part_bytes))
    return [items.where(F.pmod(F.xxhash64("text"), F.lit(n)) == k) if n > 1 else items for k in range(n)]


HITS = T.StructType(
    [
        T.StructField("n_words", T.LongType()),
        T.StructField("words", T.ArrayType(T.LongType())),
        T.StructField("starts", T.ArrayType(T.LongType())),
        T.StructField("ends", T.ArrayType(T.LongType())),
        T.StructField("items", T.ArrayType(T.StringType())),
    ]
)
_HITS = pa.struct([("n_words", pa.int64()), *((c, pa.list_(pa.int64())) for c in ("words", "starts", "ends")), ("items", pa.list_(pa.string()))])


def scan(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, part_bytes: int = PART_BYTES, into: str = "hits", clean: bool = False) -> DataFrame:
    """``docs`` with a struct ``into``: n_words; for each word inside a window its number, first byte and end in the text
    (``words``, ``starts``, ``ends``); and the sorted ids of the items met (``items``).  clean: instead, the rows that are not
    contaminated, as they were."""
    schema = T.StructType([*docs.schema.fields, T.StructField(into, HITS)])
    parts = parts_of(benchmark, part_bytes)
    for k, part in enumerate(parts):
        docs = _pass(docs, part, window, schema, k > 0, clean and k == len(parts) - 1)
        if len(parts) > 1:
            docs = cut(docs)
    return docs


def _pass(docs: DataFrame, part: DataFrame, window: int, schema: T.StructType, begun: bool, clean: bool) -> DataFrame:
    table = part.toArrow().combine_chunks()
    texts = table.column("text")
    windows = WindowSet(pa.concat_arrays(texts.chunks) if texts.num_chunks != 1 else texts.chunk(0), window)
    names = [None if x is None else str(x) for x in table.column("item_id").to_pylist()]
    del table, texts
    shared, names_shared = sent(docs, windows), docs.sparkSession.sparkContext.broadcast(names)

    def run(batches):
        windows, names = opened(WindowSet, shared), names_shared.value
        for batch in batches:
            before = batch.column(batch.num_columns - 1).to_pylist() if begun else None
            own = batch.select(list(range(len(schema.fields) - 1)))
            for a, b, raw, offsets in text_blocks(batch, "text", BLOCK):
                starts, ends, row, hit, items = scan_block(raw, offsets, windows)
                counts = np.bincount(row, minlength=b - a)
                first = np.cumsum(counts) - counts
                out = [{"n_words": n, "words": [], "starts": [], "ends": [], "items": []} for n in counts.tolist()]
                for r, found in items.items():
                    at = np.flatnonzero(hit[first[r] : first[r] + counts[r]])
                    k = at + first[r]
                    out[r] |= {"words": at.tolist(), "starts": (starts[k] - offsets[r]).tolist(), "ends": (ends[k] - offsets[r]).tolist()}
                    out[r]["items"] = sorted({names[x] for x in found} - {None})
                if before:
                    out = [_joined(x, y) for x, y in zip(before[a:b], out, strict=True)]
                if clean:
                    yield own.slice(a, b - a).filter(pa.array([not is_contaminated(len(x["words"]), x["n_words"]) for x in out], pa.bool_()))
                    continue
                yield pa.RecordBatch.from_arrays([*(c for c in own.slice(a, b - a).columns), pa.array(out, _HITS)], schema.fieldNames())

    return docs.mapInArrow(run, T.StructType(schema.fields[:-1]) if clean else schema)


def _joined(x: dict, y: dict) -> dict:
    """The hits of two parts."""
    if not y["words"] and not y["items"]:
        return x
    spans = sorted({*zip(x["words"], x["starts"], x["ends"], strict=True), *zip(y["words"], y["starts"], y["ends"], strict=True)})
    words, starts, ends = zip(*spans, strict=True) if spans else ((), (), ())
    return {"n_words": y["n_words"], "words": words, "starts": starts, "ends": ends, "items": sorted({*x["items"], *y["items"]})}


def is_contaminated(n_hit, n_words):
    """The rule, for numbers and columns: at least one hit word, and at least a twentieth of all words."""
    return (n_hit > 0) & (n_hit * 20 >= n_words)


def report(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, part_bytes: int = PART_BYTES) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated for each document."""
    n_hit, n_words = F.size("hits.words").cast("long"), F.col("hits.n_words")
    return scan(docs.select("doc_id", "text"), benchmark, window, part_bytes).select(
        "doc_id",
        n_words.alias("n_words"),
        n_hit.alias("n_hit"),
        F.size("hits.items").cast("long").alias("n_items"),
        F.sha2(F.array_join("hits.items", ",").cast("binary"), 256).alias("items_sha256"),
        is_contaminated(n_hit, n_words).alias("contaminated"),
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, part_bytes: int = PART_BYTES) -> DataFrame:
    """The documents that the rule leaves, all columns as they were; judged row by row, without a join."""
    return scan(docs, benchmark, window, part_bytes, free_name("hits", docs.columns), clean=True)


def remove_spans(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, part_bytes: int = PART_BYTES) -> DataFrame:
    """All documents, runs of hit words cut out of ``text``; null texts stay null, other columns as they were."""
    name = free_name("hits", docs.columns)

    def run(batches):
        for batch in batches:
            at = batch.schema.get_field_index("text")
            texts = batch.column(at).to_pylist()
            for r, hits in enumerate(batch.column(batch.num_columns - 1).to_pylist()):
                if hits["words"]:
                    raw = texts[r].encode()
                    keep = np.ones(len(raw), bool)
                    last = last_end = None
                    for w, a, b in zip(hits["words"], hits["starts"], hits["ends"], strict=True):
                        keep[last_end if last == w - 1 else a : b] = False
                        last, last_end = w, b
                    texts[r] = np.frombuffer(raw, np.uint8)[keep].tobytes().decode("utf-8", "replace")
            changed = batch.set_column(at, batch.schema.field(at), pa.array(texts, batch.schema.field(at).type))
            yield changed.select(list(range(batch.num_columns - 1)))

    return scan(docs, benchmark, window, part_bytes, name).mapInArrow(run, docs.schema)
