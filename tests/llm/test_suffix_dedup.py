"""Suffix arrays, common prefixes and the removal of repeated strings, against brute force."""

import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from ruleclosure.llm import suffix_dedup as S


def brute(docs):
    data = [(i, (t or "").encode()) for i, t in docs]
    seen = Counter(d[k : k + 200] for _, d in data for k in range(len(d) - 199))
    out = []
    for i, d in data:
        gone = np.zeros(len(d) + 1, bool)
        for k in range(len(d) - 199):
            if seen[d[k : k + 200]] > 1:
                gone[k : k + 200] = True
        runs = int((np.diff(np.concatenate([[0], gone[: len(d)].astype(int)])) == 1).sum())
        out.append((i, len(d), int(gone.sum()), runs, hashlib.sha256(bytes(b for b, g in zip(d, gone, strict=False) if not g)).hexdigest()))
    return sorted(out, key=repr)


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


@pytest.mark.parametrize("depth", [1, 20, 200, 5000])
def test_suffix_array_sorts_to_its_depth(depth):
    rng = np.random.default_rng(depth)
    data = np.concatenate([rng.integers(0, 3, 500), np.zeros(300), rng.integers(0, 257, 200), rng.integers(0, 2, 50)]).astype(np.int16)
    order = S.suffix_array(data, depth)
    assert sorted(order.tolist()) == list(range(len(data)))
    heads = [data[k : k + depth].tolist() for k in order.tolist()]
    assert all(a[:depth] <= b[:depth] for a, b in zip(heads[:-1], heads[1:], strict=True))


def test_regions_are_sorted_whole_and_common_prefixes_equal_a_plain_loop():
    rng = np.random.default_rng(4)
    parts = [rng.integers(0, 2, 300), np.zeros(100), rng.integers(0, 2, 300), rng.integers(0, 2, 7), np.zeros(100), [], rng.integers(0, 2, 40)]
    parts[4], parts[6] = parts[1], parts[0][100:180]
    sizes = np.array([len(x) for x in parts])
    starts = np.cumsum(sizes + 1) - sizes - 1
    raw = np.concatenate([np.append(x, 0) for x in parts]).astype(np.uint8)
    region = np.repeat(np.arange(len(parts)), sizes + 1)
    left = sizes[region] - np.arange(len(raw)) + starts[region]
    data = raw.astype(np.int16)
    data[left == 0] = 256
    order = S.suffix_array(data, None, left)
    whole = [(*data[k : k + left[k]].tolist(), 256 + int(region[k])) for k in range(len(raw))]
    assert [whole[k] for k in order.tolist()] == sorted(whole)
    wanted = np.array([300, 60, 300, 7, 100, 0, 1])
    lcp = S.common_prefixes(raw, order, left, starts, wanted, 60)
    inside = {k for a, n in zip(starts, wanted, strict=True) for k in range(a, a + n)}
    for k in range(1, len(order)):
        i, j, m = int(order[k]), int(order[k - 1]), 0
        while m < min(60, left[i], left[j]) and data[i + m] == data[j + m]:
            m += 1
        assert lcp[k] == (m if i in inside else 0)


def texts(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefg é") for _ in range(rng.randrange(2, 9)))
    prose = lambda n: " ".join(word() for _ in range(n))
    passages = [prose(60), prose(45), prose(200), "ab" * 150, "x" * 201, "y" * 200]
    out = []
    for _ in range(60):
        parts = [prose(rng.randrange(0, 80)) for _ in range(rng.randrange(0, 4))]
        if rng.random() < 0.6:
            p = rng.choice(passages)
            cut = rng.randrange(0, 60)
            parts.insert(rng.randrange(0, len(parts) + 1), p[cut : len(p) - rng.randrange(0, 30)])
        out.append(rng.choice(["", " ", "\n"]).join(parts))
    near = list(prose(300))
    for k in range(12):
        near[rng.randrange(len(near))] = "#"
        out.append("".join(near) if k % 3 else "".join(near[: len(near) // 2]))
    return [*out, out[5], out[7], None, ""]


@pytest.mark.parametrize("seed", [1, 2])
def test_removal_equals_brute_force(spark, seed):
    data = list(enumerate(texts(seed)))
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(4)
    assert rows(S.report(df)) == brute(data)
    left = {r.doc_id: r.text for r in S.remove(df).collect()}
    assert left[data[-1][0]] == "" and len(left) == len(data)


def test_removal_equals_brute_force_on_tables(docs):
    assert rows(S.report(docs)) == brute([tuple(r) for r in docs.select("doc_id", "text").collect()])


def test_odd_rows(odd, none):
    assert rows(S.report(odd)) == brute([tuple(r) for r in odd.select("doc_id", "text").collect()])
    assert S.report(none).count() == 0


@pytest.mark.parametrize("shard", [900, 6_000])
def test_large_anchors_over_several_shards(spark, shard):
    """One line in 300 different settings: its anchors have many times the regions of a shard."""
    rng = random.Random(9)
    word = lambda n: "".join(rng.choice("abcdefghij ") for _ in range(n))
    line, halves = word(190), [word(150), word(150)]
    data = [(k, word(rng.randrange(0, 200)) + rng.choice(halves)[rng.randrange(0, 60) :] + line + rng.choice(halves)[: rng.randrange(1, 120)] + word(150)) for k in range(300)]
    data += [(1000, data[0][1]), (1001, line + line)]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    assert rows(S.report(df, shard)) == brute(data)


@pytest.mark.parametrize("hot", [0, 10])
def test_regions_of_many_copies(spark, monkeypatch, hot):
    monkeypatch.setattr(S, "HOT_COPIES", hot)
    monkeypatch.setattr(S, "HOT_SHARE", 10**9 if hot == 0 else 2_000)
    data = list(enumerate(texts(1)[:30] + [texts(1)[5]] * 20))
    assert rows(S.report(spark.createDataFrame(data, "doc_id long, text string"))) == brute(data)


def test_keys_met_by_search_equal_a_plain_count():
    rng = np.random.default_rng(2)
    runs, places = [], {}
    for _ in range(6):
        keys = np.unique(rng.integers(0, 60, 25).astype("S16"))
        low = rng.integers(0, 4, len(keys)).astype(np.uint64)
        high = low + rng.integers(0, 2, len(keys)).astype(np.uint64)
        runs.append((keys, low, high))
        for k, a, b in zip(keys.tolist(), low.tolist(), high.tolist(), strict=True):
            places.setdefault(k, set()).update((a, b))
    for (keys, _, _), good in zip(runs, S.met_by_search(runs), strict=True):
        assert good.tolist() == [len(places[k]) > 1 for k in keys.tolist()]


def test_a_region_of_several_copies_repeats():
    rng = random.Random(3)
    text = bytes(rng.randrange(97, 123) for _ in range(260))
    one, other = S.repeats([text, text[::-1]], np.array([7, 99], np.uint64), np.array([True, False]))
    assert one.all() and not other.any()


def test_nothing_goes_but_by_suffix_arrays(spark, monkeypatch):
    data = list(enumerate(texts(1)))
    monkeypatch.setattr(S, "repeats", lambda texts, places, several=None, window=200: [np.zeros(max(0, len(t) - window + 1), bool) for t in texts])
    assert not [r for r in S.report(spark.createDataFrame(data, "doc_id long, text string")).collect() if r.n_removed]


def test_other_bytes_under_the_same_hashes_stay():
    text = bytes(range(97, 123)) * 20
    cut = {"loc": 10 << 18 | 5 << 9 | 250, "sum": S.digest(text[5:255]), "spans": [{"a": 0, "b": 200}]}
    assert S.keep_mask(text, [cut]).sum() == len(text) - 200
    assert S.keep_mask(text, [cut | {"sum": S.digest(b"x")}]).all()


def test_one_place_in_two_regions_is_no_repeat():
    rng = random.Random(3)
    text = bytes(rng.randrange(97, 123) for _ in range(400))
    found = S.repeats([text[:300], text[50:400]], np.array([7, 57], np.uint64))
    assert not any(f.any() for f in found)
