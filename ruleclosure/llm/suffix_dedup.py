"""Exact substring deduplication with suffix arrays.

Every byte covered by a 200-byte string that also starts anywhere else is removed.  Documents are too many for one
suffix array, and comparing arrays of document shards pair by pair would grow with the square of their number; so
shards are cut by content instead:

1. In every 200-byte window the 32-byte gram with the smallest hash is its *anchor*.  Equal windows have equal
   anchors at equal places.  Anchors, about one in 85 bytes, are kept with a hash of their *region*, the bytes of all
   windows around them.
2. Only anchors that occur twice can lie in a repeated window; one exchange of all anchors finds them.
3. Of each distinct region of such an anchor one copy, with the number of copies, goes to the shard that owns the anchor.
   Regions that occur once and no stretch of which occurs twice in the shard are set aside; of all others a shard sorts
   the suffixes by Larsson and Sadakane's refinement (ranks of prefixes double in length, only groups that are still tied are
   sorted again) and takes common prefixes by Kasai's method, all regions in step.  Neighbours that share 200 bytes
   from different places, or from a region of several copies, are repeats.
4. The regions of an anchor that outgrow a shard are dealt by their hash into several.  Each shard's different window keys,
   sorted, meet those of the others over ranges of keys, where they are merged by binary search; keys that two
   shards hold return to them.
5. Verdicts return to all occurrences of their region, and per document to its bytes.

Hashes only choose and group candidates: a document compares a 128-bit BLAKE2b digest of the region that was judged with that of its
own bytes before any go, and window keys that shards merge are such digests.

Edge cases: null is the empty text; texts under 200 bytes keep everything; repeated rows repeat each other
and lose all 200-byte strings; a document can repeat itself; runs of one character repeat themselves from 201
bytes on; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..durable import cut
from .common import BASE_B, Spans, mix, text_blocks

WINDOW = 200
GRAM = 32
SHARD_BYTES = 1_500_000
#: What a region holds on average, to know how many make a shard.
REGION_BYTES = 300
KEYS_IN_RANGE = 1_000_000
#: A region is hot if it has so many copies and more than one in ``HOT_SHARE`` of all rows: so fewer than ``HOT_SHARE`` are.
HOT_COPIES, HOT_SHARE = 1_000, 2_000
MAX_BROADCAST_ROWS = 100_000
BLOCK = 500_000

_DOC_ID, _PLACE = np.uint64(0x8CB92BA72F3D8DD7), np.uint64(0xA0761D6478BD642F)


def sliding(values: np.ndarray, width: int, best) -> np.ndarray:
    """``best`` (np.minimum or np.maximum) of each run of ``width`` values, by running bests of blocks."""
    n = len(values)
    pad = -n % width
    edge = np.iinfo(values.dtype).max if best is np.minimum else 0
    rows = np.concatenate([values, np.full(pad, edge, values.dtype)]).reshape(-1, width)
    ahead = best.accumulate(rows, axis=1).ravel()
    behind = best.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    return best(behind[: n - width + 1], ahead[width - 1 : n])


def anchors(raw: np.ndarray, offsets: np.ndarray, window: int = WINDOW, gram: int = GRAM):
    """(row, place in the text, bytes of the region before the anchor, region size, anchor hash, region hash)."""
    n, width = len(raw), window - gram + 1
    if n < window:
        none = np.zeros(0, np.int64)
        return none, none, none, none, none.astype(np.uint64), none.astype(np.uint64)
    sums = Spans(raw)
    grams = mix((sums.sums[gram:] - sums.sums[: n + 1 - gram]) * sums.undo[: n + 1 - gram])
    order = (grams >> np.uint64(32)).astype(np.uint32) | np.uint32(1)
    low = sliding(order, width, np.minimum)
    for end in offsets[1:-1].tolist():  # windows that leave their text
        low[max(0, end - window + 1) : end] = 0
    wide = np.zeros(len(low) + 2 * width - 2, np.uint32)
    wide[width - 1 : width - 1 + len(low)] = low
    at = np.flatnonzero(sliding(wide, width, np.maximum) == order)
    # Each window belongs to the leftmost of its smallest grams; an anchor's region is what its windows cover.
    x = np.flatnonzero(low)
    k = np.searchsorted(at, x)
    wrong = np.flatnonzero(order[at[k]] != low[x])
    while len(wrong):
        k[wrong] += 1
        wrong = wrong[order[at[k[wrong]]] != low[x[wrong]]]
    begin = np.flatnonzero(np.diff(k, prepend=-1))
    last = np.append(begin[1:], len(k)) - 1
    at, begin, end = at[k[begin]] if len(k) else at[:0], x[begin], x[last] + window if len(k) else x[:0]
    row = np.searchsorted(offsets, at, side="right") - 1
    start, before = offsets[row], at - begin
    region = mix(Spans(raw, BASE_B).hash(at - before, end) + before.astype(np.uint64) * _PLACE)
    return row, at - start, before, end - at + before, grams[at], region


def row_keys(ids: pa.Array, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One key for each (doc_id, text)."""
    known = np.array([hash_id(x) for x in ids.to_pylist()], np.uint64)
    return mix(Spans(raw, int(_DOC_ID)).hash(offsets[:-1], offsets[1:]) + known * _PLACE + np.diff(offsets).astype(np.uint64))


def hash_id(x) -> int:
    return 1 if x is None else int.from_bytes(hashlib.blake2b(str(x).encode(), digest_size=8).digest(), "big")


def find_anchors(docs: DataFrame) -> DataFrame:
    """rk (document), loc (place, bytes before, size in one number), ha, hr, and ``lot``, by which the row is dealt.

    An anchor that a batch holds several times needs no other to prove it: but for the first, such rows are dealt by
    chance (``sure``), so a passage of very many documents never meets in one task.
    """

    def run(batches):
        for batch in batches:
            found = []
            for a, b, raw, offsets in text_blocks(batch, "text", BLOCK):
                keys = row_keys(batch.column(0).slice(a, b - a), raw, offsets)
                row, place, before, size, ha, hr = anchors(raw, offsets)
                found.append((keys[row], (place << 18 | before << 9 | size).view(np.uint64), ha, hr))
            if found:
                rk, loc, ha, hr = (np.concatenate(x) for x in zip(*found, strict=True))
                _, first, back, n = np.unique(ha, return_index=True, return_inverse=True, return_counts=True)
                sure = n[back] > 1
                lot = np.where(sure, mix(rk + loc * _PLACE), ha)
                lot[first] = ha[first]
                for a in range(0, len(rk), 50_000):
                    part = [pa.array(x[a : a + 50_000].view(np.int64)) for x in (rk, loc, ha, hr, lot)]
                    yield pa.RecordBatch.from_arrays([*part, pa.array(sure[a : a + 50_000])], ["rk", "loc", "ha", "hr", "lot", "sure"])

    return docs.select("doc_id", "text").mapInArrow(run, "rk long, loc long, ha long, hr long, lot long, sure boolean")


def repeated_anchors(docs: DataFrame) -> DataFrame:
    """Anchors that occur more than once, found by one exchange of all."""

    def run(batches):
        held = None  # a batch ends where its last lot may go on
        for batch in batches:
            rows = pa.Table.from_batches([batch])
            table = rows if held is None else pa.concat_tables([held, rows])
            lot = table.column("lot").to_numpy()
            last = int(np.searchsorted(lot, lot[-1])) if len(lot) else 0
            yield from kept(table.slice(0, last)).to_batches()
            held = table.slice(last)
        if held is not None:
            yield from kept(held).to_batches()

    def kept(table):
        lot = table.column("lot").to_numpy()
        sure = table.column("sure").to_numpy()
        same = np.zeros(len(lot), bool)
        if len(lot):
            equal = lot[1:] == lot[:-1]
            same[1:] |= equal
            same[:-1] |= equal
        return table.filter(pa.array(sure | same)).select(["rk", "loc", "ha", "hr"])

    return find_anchors(docs).repartition("lot").sortWithinPartitions("lot").mapInArrow(run, "rk long, loc long, ha long, hr long")


def packed_texts(docs: DataFrame) -> DataFrame:
    """rk, doc_id, z (the compressed text), to be moved by rk."""
    schema = T.StructType([T.StructField("rk", T.LongType()), docs.schema["doc_id"], T.StructField("z", T.BinaryType())])

    def run(batches):
        press = zstandard.ZstdCompressor(level=3)
        for batch in batches:
            for a, b, raw, offsets in text_blocks(batch, "text", BLOCK):
                ids = batch.column(0).slice(a, b - a)
                z = [press.compress(raw[x:y].tobytes()) for x, y in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(row_keys(ids, raw, offsets).view(np.int64)), ids, pa.array(z, pa.binary())], ["rk", "doc_id", "z"])

    return docs.select("doc_id", "text").mapInArrow(run, schema)


# --- suffix arrays of one shard


def suffix_array(data: np.ndarray, depth: int | None = None, left: np.ndarray | None = None) -> np.ndarray:
    """Starts of all suffixes of ``data`` (small integers), in full order or by at least ``depth`` first values.

    left: how many values stand before the end of each suffix's region, whose last value is a separator; separators differ
    from each other, in the order of their places, so suffixes that reach theirs are sorted.
    """
    n = len(data)
    depth = depth or n
    # As many first values as fit one word, in as few bits as the alphabet takes.
    used = np.flatnonzero(np.bincount(data.astype(np.int64), minlength=1))
    bits = max(1, int(len(used)).bit_length())
    h = 64 // bits
    code = np.zeros(int(used[-1]) + 1 if len(used) else 1, np.uint64)
    code[used] = np.arange(1, len(used) + 1)
    wide = np.zeros(n + h, np.uint64)
    wide[:n] = code[data]
    key = np.zeros(n, np.uint64)
    for k in range(h):
        key = key << np.uint64(bits) | (wide[k : k + n] if left is None else np.where(left >= k, wide[k : k + n], 0))
    order = np.argsort(key, kind="stable")
    ranked = key[order]
    new = np.concatenate([[True], ranked[1:] != ranked[:-1]])
    if left is not None:
        new |= left[order] < h
    begin = np.flatnonzero(new)
    rank = np.empty(n + 1, np.int64)
    del key, ranked, wide
    size = np.diff(np.append(begin, n))
    rank[order] = np.repeat(begin, size)
    rank[n] = -1
    open_at = np.flatnonzero(np.repeat(size > 1, size))  # places in the order that are still tied
    while h < depth and len(open_at):
        tied = order[open_at]
        own, after = rank[tied], rank[np.minimum(tied + h, n)]
        both = own.astype(np.uint64) * np.uint64(n + 1) + (after + 1).astype(np.uint64)
        inner = np.argsort(both, kind="stable")
        tied, both = tied[inner], both[inner]
        order[open_at] = tied  # groups keep their places, members change
        new = np.concatenate([[True], both[1:] != both[:-1]])
        begin = np.flatnonzero(new)
        size = np.diff(np.append(begin, len(tied)))
        rank[tied] = np.repeat(open_at[begin], size)
        open_at = open_at[np.repeat(size > 1, size)]
        h *= 2
    return order


def common_prefixes(raw: np.ndarray, order: np.ndarray, left: np.ndarray, starts: np.ndarray, wanted: np.ndarray, cap: int) -> np.ndarray:
    """lcp[k]: common prefix, up to ``cap``, of the suffixes at order[k-1] and order[k], for the ``wanted`` first suffixes of each
    region; prefixes end with their region.  Kasai's method, all regions in step: a prefix shrinks by at most one from one suffix
    to the next; it grows by eight bytes at a time."""
    n = len(raw)
    place = np.empty(n, np.int64)
    place[order] = np.arange(n)
    before = np.full(n, -1, np.int64)
    before[order[1:]] = order[:-1]
    word = np.ndarray((n,), "<u8", np.concatenate([raw, np.zeros(8, np.uint8)]), strides=(1,)).copy()
    lcp = np.zeros(n, np.int64)
    longest = np.argsort(-wanted, kind="stable")
    starts, wanted = starts[longest], wanted[longest]
    length = np.zeros(len(starts), np.int64)
    for t in range(int(wanted.max(initial=0))):
        live = int(np.searchsorted(-wanted, -t, side="left"))  # those with more than t
        i = starts[:live] + t
        j = before[i]
        most = np.where(j >= 0, np.minimum(np.minimum(left[i], left[j]), cap), 0)
        m = np.minimum(np.maximum(length[:live] - 1, 0), most)
        grow = np.flatnonzero(m < most)
        while len(grow):
            differ = word[i[grow] + m[grow]] ^ word[j[grow] + m[grow]]
            lowest = differ & (~differ + np.uint64(1))  # the lowest bit that differs, a power of two
            run = np.where(differ == 0, 8, np.log2(np.maximum(lowest, 1).astype(np.float64)).astype(np.int64) >> 3)
            m[grow] = np.minimum(m[grow] + run, most[grow])
            grow = grow[(run == 8) & (m[grow] < most[grow])]
        length[:live] = m
        lcp[place[i]] = m
    return lcp


def repeats(texts: list[bytes], places: np.ndarray, several: np.ndarray | None = None, window: int = WINDOW) -> list[np.ndarray]:
    """For each region: which of its windows occur at another place.  places: a 64-bit name for each region's first
    byte such that equal bytes of one document have equal names in all regions (name + offset).  several: regions that stand for
    more than one copy."""
    sizes = np.array([len(t) for t in texts], np.int64)
    starts = np.cumsum(sizes + 1) - sizes - 1
    n = int((sizes + 1).sum())
    region = np.repeat(np.arange(len(texts)), sizes + 1)
    offset = np.arange(n) - starts[region]
    left = sizes[region] - offset
    raw = np.zeros(n, np.uint8)
    raw[left > 0] = np.frombuffer(b"".join(texts), np.uint8)
    data = raw.astype(np.int16)
    data[left == 0] = 256
    # Kasai's method needs the full order: ties would break the bound from one suffix to the next.
    order = suffix_array(data, None, left)
    lcp = common_prefixes(raw, order, left, starts, np.maximum(0, sizes - window + 1), window)
    # Runs of suffixes that share a window's length; a run from one place only is no repeat.
    run_begin = np.flatnonzero(lcp < window)
    names = (places[region] + offset.astype(np.uint64))[order]
    low, high = np.minimum.reduceat(names, run_begin), np.maximum.reduceat(names, run_begin)
    again = low != high
    if several is not None:
        again |= np.logical_or.reduceat(several[region[order]], run_begin)
    found = np.zeros(n, bool)
    found[order] = np.repeat(again, np.diff(np.append(run_begin, n)))
    found &= left >= window
    return [found[a : a + max(0, m - window + 1)] for a, m in zip(starts.tolist(), sizes.tolist(), strict=True)]


def promising(texts: list[bytes], before: np.ndarray, window: int = WINDOW, gram: int = GRAM, cases: int = 8) -> np.ndarray:
    """Whether a region may hold a repeated window, seen without sorting.

    A window holds ``a`` bytes before the anchor; by ``a`` it falls into one of ``cases`` ranges, and all windows of a range
    share a stretch around the anchor.  Where none of a region's stretches occurs twice, none of its windows does.
    """
    sizes = np.array([len(t) for t in texts], np.int64)
    starts = np.cumsum(sizes) - sizes
    sums = Spans(np.frombuffer(b"".join(texts), np.uint8))
    width = window - gram + 1
    out = np.zeros(len(texts), bool)
    for k in range(cases):
        least, most = width * k // cases, width * (k + 1) // cases - 1
        # Regions with a window of this range; the common stretch lies inside such a window.
        some = np.flatnonzero(np.maximum(least, before - sizes + window) <= np.minimum(most, before))
        lo = starts[some] + before[some] - least
        _, back, n = np.unique(sums.hash(lo, lo + window - (most - least)), return_inverse=True, return_counts=True)
        out[some] |= n[back] > 1
    return out


def digest(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


def window_keys(texts: list[bytes], window: int = WINDOW) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(keys, region, offset) of all windows; a key is a digest as two words (most significant first, in order)."""
    cells = [(digest(t[x : x + window]), k, x) for k, t in enumerate(texts) for x in range(len(t) - window + 1)]
    raw = np.frombuffer(b"".join(c[0] for c in cells), ">u8").astype(np.uint64).reshape(-1, 2)
    return raw, np.array([c[1] for c in cells], np.int64), np.array([c[2] for c in cells], np.int64)


def packed_keys(keys: np.ndarray) -> np.ndarray:
    """Keys as one sortable value each."""
    return np.ascontiguousarray(keys.astype(">u8")).view("S16").ravel()


def met_by_search(runs: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> list[np.ndarray]:
    """For each run (sorted different keys, lowest and highest place of each key): which of its keys stand at another
    place too, in any run.  Runs are merged one by one into what was merged before, by binary search."""
    merged, low, high = np.zeros(0, "S16"), np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    for keys, a, b in runs:
        at = np.searchsorted(merged, keys)
        same = np.zeros(len(keys), bool)
        inside = at < len(merged)
        same[inside] = merged[at[inside]] == keys[inside]
        low[at[same]], high[at[same]] = np.minimum(low[at[same]], a[same]), np.maximum(high[at[same]], b[same])
        rest = ~same
        merged, low, high = (np.insert(x, at[rest], y[rest]) for x, y in ((merged, keys), (low, a), (high, b)))
    out = []
    for keys, _, _ in runs:
        at = np.searchsorted(merged, keys)
        out.append(low[at] != high[at])
    return out


def spans_of(found: np.ndarray, window: int = WINDOW) -> list[tuple[int, int]]:
    """Covered byte ranges of a region from its repeated windows."""
    if not found.any():
        return []
    at = np.flatnonzero(found)
    gap = np.flatnonzero(np.diff(at) > window)
    begin, end = at[np.concatenate([[0], gap + 1])], at[np.concatenate([gap, [len(at) - 1]])] + window
    return list(zip(begin.tolist(), end.tolist(), strict=True))


SPANS = "array<struct<a:int,b:int>>"


REGION = "ha long, part int, hr long, place long, n long, region binary, before long"


def judge_regions(regions: DataFrame, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """ha, hr, sum (digest), spans: covered ranges of regions (those without are left out).  ``regions`` (see REGION) and, with no region
    but in ``keys``, what other shards of the anchor hold too; dealt and sorted by ha, part, and keys first."""
    kind = pa.list_(pa.struct([("a", pa.int32()), ("b", pa.int32())]))

    def verdicts(shard, found):
        rows = [(x[0], x[2], digest(x[5]), [{"a": a, "b": b} for a, b in spans]) for x, f in zip(shard, found, strict=True) if (spans := spans_of(f))]
        if rows:
            ha, hr, sums, spans = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(ha, pa.int64()), pa.array(hr, pa.int64()), pa.array(sums, pa.binary()), pa.array(spans, kind)], ["ha", "hr", "sum", "spans"])

    def judged(shard, elsewhere=None):
        several = np.array([x[4] > 1 for x in shard])
        names = np.array([x[3] for x in shard], np.int64).view(np.uint64)
        texts = [x[5] for x in shard]
        if elsewhere is None:
            likely = promising(texts, np.array([x[6] for x in shard], np.int64)) | several
            some = np.flatnonzero(likely).tolist()
            if some:
                yield from verdicts([shard[k] for k in some], repeats([texts[k] for k in some], names[some], several[some]))
            return
        found = repeats(texts, names, several)
        keys, of, x = window_keys(texts)
        if len(keys):
            for k in np.flatnonzero(np.isin(packed_keys(keys), elsewhere)).tolist():
                found[of[k]][x[k]] = True
        yield from verdicts(shard, found)

    def run(batches):
        shard, size = [], 0  # whole groups of anchors
        group, group_size, keys, at = [], 0, [], None

        def close():
            nonlocal shard, size, group, group_size, keys
            if keys or (at is not None and at[1] is not None and at[1] >= 0):  # one of several shards of its anchor
                if group:
                    yield from judged(group, np.array(keys, "S16") if keys else np.zeros(0, "S16"))
            elif group:
                if shard and size + group_size > shard_bytes:
                    yield from judged(shard)
                    shard, size = [], 0
                shard, size = shard + group, size + group_size
            group, group_size, keys = [], 0, []

        for batch in batches:
            for row in zip(*(batch.column(k).to_pylist() for k in range(8)), strict=True):
                if row[:2] != at:
                    yield from close()
                    at = row[:2]
                if row[7] is not None:
                    raw = row[7]
                    keys += [raw[k : k + 16] for k in range(0, len(raw), 16)]
                else:
                    group.append(row)
                    group_size += len(row[5])
        yield from close()
        if shard:
            yield from judged(shard)

    return regions.select("ha", "part", "hr", "place", "n", "region", "before", "keys").mapInArrow(run, f"ha long, hr long, sum binary, spans {SPANS}")


def shared_keys(regions: DataFrame) -> DataFrame:
    """ha, part, keys (digests one after another): windows of the shards of an anchor that another of its shards holds too."""

    def keyed(batches):
        def out(group, at):
            texts, names = [x[5] for x in group], np.array([x[3] for x in group], np.int64).view(np.uint64)
            keys, of, x = window_keys(texts)
            if not len(keys):
                return
            packed, places = packed_keys(keys), names[of] + x.astype(np.uint64)
            order = np.lexsort((places, packed))
            packed, places = packed[order], places[order]
            begin = np.flatnonzero(np.concatenate([[True], packed[1:] != packed[:-1]]))
            last = np.append(begin[1:], len(packed)) - 1
            hi, lo = (keys[order][begin][:, k].view(np.int64) for k in (0, 1))
            for a in range(0, len(begin), 50_000):
                cells = [x[a : a + 50_000] for x in (hi, lo, places[begin].view(np.int64), places[last].view(np.int64))]
                yield pa.RecordBatch.from_arrays([*(pa.array(c) for c in cells), *(pa.array(np.full(len(cells[0]), v), t) for v, t in zip(at, (pa.int64(), pa.int32()), strict=True))], ["k1", "k2", "low", "high", "ha", "part"])

        group, at = [], None
        for batch in batches:
            for row in zip(*(batch.column(k).to_pylist() for k in range(7)), strict=True):
                if row[:2] != at:
                    yield from out(group, at)
                    group, at = [], row[:2]
                group.append(row)
        yield from out(group, at)

    def merged(batches):
        """A range of keys, all runs in it, by anchor and part."""
        rows = [np.concatenate(x) for x in zip(*[[batch.column(k).to_numpy() for k in range(6)] for batch in batches], strict=True)]
        if not rows or not len(rows[0]):
            return
        k1, k2, low, high, ha, part = rows
        packed = packed_keys(np.stack([k1.view(np.uint64), k2.view(np.uint64)], axis=1))
        order = np.lexsort((packed, part, ha))
        names = np.stack([ha, part], axis=1)[order]
        begin = np.flatnonzero(np.concatenate([[True], (names[1:] != names[:-1]).any(axis=1)]))
        cuts = [*begin.tolist(), len(order)]
        runs = [(packed[o], low[o].view(np.uint64), high[o].view(np.uint64)) for o in (order[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True))]
        for a, (keys, _, _), good in zip(cuts[:-1], runs, met_by_search(runs), strict=True):
            if good.any():
                raw = np.ascontiguousarray(keys[good]).tobytes()
                yield pa.RecordBatch.from_arrays([pa.array([names[a][0]]), pa.array([names[a][1]], pa.int32()), pa.array([raw], pa.binary())], ["ha", "part", "keys"])

    rows = cut(regions.repartition("ha", "part").sortWithinPartitions("ha", "part").select("ha", "part", "hr", "place", "n", "region", "before").mapInArrow(keyed, "k1 long, k2 long, low long, high long, ha long, part int"))
    ranges = 1 + rows.count() // KEYS_IN_RANGE
    return rows.repartitionByRange(ranges, "k1").mapInArrow(merged, "ha long, part int, keys binary")


def extract(wanted: DataFrame) -> DataFrame:
    """ha, part, hr, place, n, region, before from rows of (rk, z, asked: array of (ha, part, hr, loc, n))."""

    def run(batches):
        open_ = zstandard.ZstdDecompressor()
        for batch in batches:
            for rk, z, asked in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                text = open_.decompress(z)
                out = []
                for x in asked:
                    place, before, size = x["loc"] >> 18, x["loc"] >> 9 & 511, x["loc"] & 511
                    a = place - before
                    out.append((x["ha"], x["part"], x["hr"], ((rk & (1 << 64) - 1) + a + (1 << 63)) % (1 << 64) - (1 << 63), x["n"], text[a : a + size], before))
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], ["ha", "part", "hr", "place", "n", "region", "before"])

    return wanted.select("rk", "z", "asked").mapInArrow(run, REGION)


def covered(docs: DataFrame, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """rk and cuts (array of loc, sum, spans: a region of the document, the digest of the judged one, covered ranges in it) of the
    documents that hold repeated strings."""
    again = cut(repeated_anchors(docs))
    regions = again.groupBy("ha", "hr").agg(F.count("*").alias("n"), F.min(F.struct("rk", "loc")).alias("at"))
    regions = cut(regions.select("ha", "hr", "n", "at.rk", "at.loc"))
    # Anchors with more regions than a shard holds go to several shards: part 0, 1, ..; all others are whole (part -1).
    most = max(1, shard_bytes // REGION_BYTES)
    large = cut(regions.groupBy("ha").agg(F.count("*").alias("k")).where(F.col("k") > most))
    several = not large.isEmpty()
    dealt = regions.withColumn("part", F.lit(-1))
    if several:
        side = large.select(F.col("ha").alias("h"), F.ceil(F.col("k") / most).cast("int").alias("parts"))
        side = F.broadcast(side) if large.count() <= MAX_BROADCAST_ROWS else side
        dealt = regions.join(side, F.col("ha") == F.col("h"), "left").withColumn("part", F.coalesce(F.pmod(F.xxhash64("hr"), F.col("parts")).cast("int"), F.lit(-1)))
    asked = dealt.groupBy("rk").agg(F.collect_list(F.struct("ha", "part", "hr", "loc", "n")).alias("asked"))
    # Of repeated rows one copy of the text is enough.
    texts = packed_texts(docs).select(F.col("rk").alias("k"), "z")
    fetched = extract(asked.join(texts, F.col("rk") == F.col("k")).select("rk", "z", "asked"))
    rows = fetched.withColumn("keys", F.lit(None).cast("binary"))
    if several:
        fetched = cut(fetched)
        more = shared_keys(fetched.where("part >= 0"))
        nothing = [F.lit(None).cast(t).alias(c) for c, t in (("hr", "long"), ("place", "long"), ("n", "long"), ("region", "binary"), ("before", "long"))]
        rows = fetched.withColumn("keys", F.lit(None).cast("binary")).unionByName(more.select("ha", "part", *nothing, "keys"))
    dealt = rows.repartition("ha", "part").sortWithinPartitions("ha", "part", "hr", "place")
    verdict = cut(judge_regions(dealt, shard_bytes).groupBy("ha", "hr").agg(F.min(F.struct("sum", "spans")).alias("v")).select("ha", "hr", "v.sum", "v.spans"))
    # Regions of very many copies, which are few by their number, are broadcast, so their copies stay where they are.
    often = max(HOT_COPIES, again.count() // HOT_SHARE)
    hot = cut(regions.where(F.col("n") > often).select("ha", "hr"))
    hits = again.join(F.broadcast(hot), ["ha", "hr"], "left_anti").join(verdict, ["ha", "hr"])
    hits = hits.unionByName(again.join(F.broadcast(verdict.join(F.broadcast(hot), ["ha", "hr"], "left_semi")), ["ha", "hr"]))
    hits = hits.select("rk", F.struct("loc", "sum", "spans").alias("c"))
    return hits.groupBy("rk").agg(F.collect_set("c").alias("cuts"))


def keep_mask(text: bytes, cuts: list[dict] | None) -> np.ndarray:
    """What stays of a document; a region whose bytes are not those that were judged loses nothing."""
    change = np.zeros(len(text) + 1, np.int64)
    for c in cuts or ():
        a = (c["loc"] >> 18) - (c["loc"] >> 9 & 511)
        if digest(text[a : a + (c["loc"] & 511)]) == c["sum"]:
            for x in c["spans"]:
                change[a + x["a"]] += 1
                change[a + x["b"]] -= 1
    return np.cumsum(change[:-1]) == 0


def with_kept(docs: DataFrame, each, schema, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """Rows (doc_id, text bytes, keep mask) of all documents through ``each``, a function of a list of them."""
    found = covered(docs, shard_bytes).withColumnRenamed("rk", "k")
    rows = packed_texts(docs)
    met = rows.join(found, F.col("rk") == F.col("k"), "left").select("doc_id", "z", "cuts")

    def run(batches):
        open_ = zstandard.ZstdDecompressor()
        for batch in batches:
            for a in range(0, batch.num_rows, 200):
                part = batch.slice(a, 200)
                out = []
                for doc_id, z, cuts in zip(*(part.column(k).to_pylist() for k in range(3)), strict=True):
                    text = open_.decompress(z)
                    out.append((doc_id, text, keep_mask(text, cuts)))
                yield each(out, part.column(0))

    return met.mapInArrow(run, schema)


def report(docs: DataFrame, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256."""
    longs = [T.StructField(x, T.LongType()) for x in ("n_bytes", "n_removed", "n_spans")]
    schema = T.StructType([docs.schema["doc_id"], *longs, T.StructField("kept_sha256", T.StringType())])

    def each(rows, ids):
        out = [[], [], [], []]
        for _, text, keep in rows:
            gone = ~keep
            out[0].append(len(text))
            out[1].append(int(gone.sum()))
            out[2].append(int((gone & np.concatenate([[True], keep[:-1]])).sum()) if len(text) else 0)
            out[3].append(hashlib.sha256(np.frombuffer(text, np.uint8)[keep].tobytes()).hexdigest())
        return pa.RecordBatch.from_arrays([ids, *(pa.array(x, pa.int64()) for x in out[:3]), pa.array(out[3], pa.string())], schema.fieldNames())

    return with_kept(docs, each, schema, shard_bytes)


def remove(docs: DataFrame) -> DataFrame:
    """doc_id and the text that is left (cut characters that lose bytes are replaced)."""
    schema = T.StructType([docs.schema["doc_id"], T.StructField("text", T.StringType())])

    def each(rows, ids):
        texts = [np.frombuffer(t, np.uint8)[keep].tobytes().decode("utf-8", "replace") for _, t, keep in rows]
        return pa.RecordBatch.from_arrays([ids, pa.array(texts, pa.string())], schema.fieldNames())

    return with_kept(docs, each, schema)
