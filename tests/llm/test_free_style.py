"""Operators on texts against brute force: decontamination, SimHash, language models, language, digests."""

import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash

from ruleclosure.llm import bloom_lm, decontaminate, language_id, quartile_digest, simhash


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


# --- decontamination


def brute_decontaminate(docs, items):
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    windows = []
    for item_id, text in items:
        w = word.findall(lower(text))
        windows += [(item_id, tuple(w[k : k + min(13, len(w))])) for k in range(max(0, len(w) - 12) or bool(w))]
    by = {}
    for item_id, w in windows:
        by.setdefault(w, set()).add(item_id)
    sizes = {len(w) for w in by}
    out = []
    for doc_id, text in docs:
        w = word.findall(lower(text))
        hit, found = [False] * len(w), set()
        for size in sizes:
            for k in range(len(w) - size + 1):
                if ids := by.get(tuple(w[k : k + size])):
                    found |= ids
                    hit[k : k + size] = [True] * size
        ids = sorted(str(x) for x in found if x is not None)
        out.append((doc_id, len(w), sum(hit), len(ids), hashlib.sha256(",".join(ids).encode()).hexdigest(), sum(hit) > 0 and 20 * sum(hit) >= len(w)))
    return sorted(out, key=repr)


def pairs(df, *columns):
    return [tuple(r) for r in df.select(*columns).collect()]


def test_decontaminate_equals_brute_force(docs, benchmark):
    assert rows(decontaminate.report(docs, benchmark)) == brute_decontaminate(pairs(docs, "doc_id", "text"), pairs(benchmark, "item_id", "text"))


def test_decontaminate_odd_rows(spark, odd, none):
    items = spark.createDataFrame([(1, "word"), (2, None), (3, ""), (None, "99"), (1, "word"), (5, "without any id")], "item_id long, text string")
    assert rows(decontaminate.report(odd, items)) == brute_decontaminate(pairs(odd, "doc_id", "text"), pairs(items, "item_id", "text"))
    assert decontaminate.report(none, items).count() == 0
    assert decontaminate.report(odd, items.limit(0)).where("contaminated").count() == 0
    kept = decontaminate.drop_contaminated(odd, items)
    assert kept.columns == odd.columns
    assert {r.doc_id for r in kept.collect()} == {0, 1, 2, 3, 4, 5, 7, 9}
    cut = {r.doc_id: r.text for r in decontaminate.remove_spans(odd, items).collect()}
    assert cut[6] == "" and cut[None] == "only text here  at all" and cut[4] is None


@pytest.mark.parametrize("limit", [1, 4_000])  # 1: three parts
def test_decontaminate_in_parts(docs, benchmark, limit):
    assert len(decontaminate.parts_of(benchmark, 4_000)) > 1
    if limit == 1:
        docs, benchmark = docs.limit(60), benchmark.limit(4)
    want = brute_decontaminate(pairs(docs, "doc_id", "text"), pairs(benchmark, "item_id", "text"))
    part = sum(len(t.encode()) for (t,) in pairs(benchmark, "text")) // 3 if limit == 1 else limit
    assert rows(decontaminate.report(docs, benchmark, part_bytes=part)) == want
    kept = decontaminate.drop_contaminated(docs, benchmark, part_bytes=part)
    assert {r.doc_id for r in kept.collect()} == {r[0] for r in want if not r[5]}


def test_windows_with_one_hash_stay_apart(monkeypatch, spark, docs, benchmark):
    import pyarrow as pa

    class Few(decontaminate.Spans):
        def hash(self, starts, ends):
            return super().hash(starts, ends) % np.uint64(7)

    monkeypatch.setattr(decontaminate, "Spans", Few)
    items, texts = pairs(benchmark, "item_id", "text")[:3], pairs(docs, "doc_id", "text")[:40]
    texts += [(1000, "so " + items[1][1] + " end")]
    windows = decontaminate.WindowSet(pa.array([t for _, t in items]))
    want = {i: (n, h, k) for i, n, h, k, _, _ in brute_decontaminate(texts, items)}
    for i, t in texts:
        raw = np.frombuffer((t or "").encode(), np.uint8)
        starts, _, _, hit, found = decontaminate.scan_block(raw, np.array([0, len(raw)]), windows)
        assert (len(starts), int(hit.sum()), len(found.get(0, ()))) == want[i]


# --- SimHash


def brute_fingerprint(text):
    w = [x for x in re.split(r"[\x20\x09-\x0D]+", lower(text)) if x]
    s = [" ".join(w[k : k + 3]) for k in range(len(w) - 2)] or ([" ".join(w)] if w else [])
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def brute_simhash(docs):
    fp = [brute_fingerprint(t) for _, t in docs]
    parent = list(range(len(docs)))

    def root(k):
        while parent[k] != k:
            k = parent[k]
        return k

    for a in range(len(fp)):
        for b in range(a):
            if (fp[a] ^ fp[b]).bit_count() <= 2:
                parent[root(a)] = root(b)
    low = {}
    for k, (i, _) in enumerate(docs):
        if i is not None:
            low[root(k)] = min(i, low.get(root(k), i))
    return sorted([(i, f"{fp[k]:016x}", low.get(root(k))) for k, (i, _) in enumerate(docs)], key=repr)


def test_simhash_equals_brute_force(docs):
    assert rows(simhash.report(docs)) == brute_simhash(pairs(docs, "doc_id", "text"))


def test_simhash_odd_rows(odd, none):
    assert rows(simhash.report(odd)) == brute_simhash(pairs(odd, "doc_id", "text"))
    assert simhash.report(none).count() == 0
    kept = simhash.keep_first(odd)
    assert kept.columns == odd.columns
    got = sorted([r.doc_id for r in kept.collect()], key=repr)
    assert got.count(None) == 1 and len(set(got)) == len(got)


def test_texts_under_one_id_are_told_apart(spark):
    a, b = "one two three four five six", "completely other words stand right here now"
    data = [(3, a, {"k": 1}, 7), (5, a, {"k": 2}, 8), (5, b, {"k": 3}, 9), (5, b, {"k": 3}, 2), (None, a, None, 1)]
    df = spark.createDataFrame(data, "doc_id long, text string, `row` map<string,int>, h int")
    seen = [sorted(((r.doc_id, r.text, r.h) for r in simhash.keep_first(df.repartition(n)).collect()), key=repr) for n in (1, 3)]
    assert seen[0] == seen[1] and [x[:2] for x in seen[0]] == [(3, a), (5, b), (None, a)]


def closure(edges):
    group = {}
    for a, b in edges:
        joined = group.get(a, {a}) | group.get(b, {b})
        for x in joined:
            group[x] = joined
    return {x: min(g) for x, g in group.items()}


@pytest.mark.parametrize("hot", [0, 2, 64])
def test_simhash_links_have_the_closure_of_all_pairs(spark, hot):
    rng = np.random.default_rng(7)
    values = {int(x) for x in rng.integers(0, 1 << 62, 30)}
    for x in list(values):
        for _ in range(20):
            x ^= 1 << int(rng.integers(0, 63))
            if rng.random() < 0.5:
                x ^= 1 << int(rng.integers(0, 63))
            values.add(x)
    table = spark.createDataFrame([(x,) for x in values], "fp long")
    every = [(a, b) for a in values for b in values if a < b and (a ^ b).bit_count() <= 2]
    found = simhash.links(table, hot=hot)
    assert closure(pairs(found, "a", "b")) == closure(every)
    assert {r.node: r.root for r in simhash.components(found).collect()} == closure(every)


def test_components_of_a_long_chain(spark):
    chain = spark.range(200).selectExpr("(id * 7919) % 200 a", "((id + 1) * 7919) % 200 b").where("a != b")
    assert {r.root for r in simhash.components(chain).collect()} == {0}


# --- language-model scores


def brute_base(docs):
    split = lambda t: [*(x for x in re.split(r"[\x20\x09-\x0D]+", lower(t)) if x), None]
    out = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 10 == 0
    c = Counter(w for i, t in docs if not out(i) for w in split(t))
    n, v = sum(c.values()), len(c)
    found = []
    for i, t in docs:
        w = split(t)
        found.append((i, out(i), len(w), sum(c[x] > 0 for x in w), n, sum(math.log10((c[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w)))
    return sorted(found, key=repr)


@pytest.mark.parametrize("limit", [1 << 28, 0])
def test_lm_base_equals_brute_force(docs, limit):
    got = rows(bloom_lm.report(docs, limit))
    want = brute_base(pairs(docs, "doc_id", "text"))
    assert [g[:5] for g in got] == [w[:5] for w in want]
    assert np.allclose([g[5] for g in got], [w[5] for w in want])


def brute_score(docs):
    """The model's scores from exact counts, quantised without a filter."""
    split = lambda t: [*(x for x in re.split(r"[\x20\x09-\x0D]+", lower(t)) if x), None]
    learned = [split(t) for i, t in docs if zlib.crc32(str(i).encode()) % 10]
    ones = Counter(w for t in learned for w in t)
    twos = Counter(x for t in learned for x in zip([None, *t], t, strict=False))
    n, v = sum(ones.values()), len(ones)

    def read(c):
        if not c:
            return 0
        q = 1 + math.floor(math.log(c, 1.5) + 1e-9)
        same = [x for x in range(1, 4 * c + 4) if 1 + math.floor(math.log(x, 1.5) + 1e-9) == q]
        return (same[0] + same[-1]) / 2

    memo = {c: read(c) for c in {*ones.values(), *twos.values(), 0}}

    def p(before, w):
        c, cv = memo[ones[w]], memo[ones[before]]
        m = 0.3 * cv / (cv + 20)
        return min(1, m * min(memo[twos[before, w]], cv) / max(cv, 1) + (1 - m) * (c + 0.1) / (n + 0.1 * (v + 1)))

    return {i: sum(math.log10(p(a, b)) for a, b in zip([None, *split(t)], split(t), strict=False)) for i, t in docs}


@pytest.mark.parametrize("lot_grams", [1 << 18, 1 << 9])
def test_lm_scores_equal_brute_force(docs, monkeypatch, lot_grams):
    monkeypatch.setattr(bloom_lm, "LOT_GRAMS", lot_grams)
    few = docs.limit(120)
    want = brute_score(pairs(few, "doc_id", "text"))
    plain = {r.doc_id: r.score for r in bloom_lm.report(few).collect()}
    monkeypatch.setattr(bloom_lm, "BITS", 64)  # so wide that no probe hits by chance
    monkeypatch.setattr(bloom_lm, "PROBES", 10)
    got = {r.doc_id: r.score for r in bloom_lm.report(few).collect()}
    assert got.keys() == want.keys() and np.allclose([got[k] for k in want], list(want.values()))
    assert np.allclose([plain[k] for k in want], list(want.values()), rtol=0.03)


def test_lm_broadcast_does_not_change_scores(docs):
    one, other = ({r.doc_id: r.score for r in bloom_lm.report(docs, x).collect()} for x in (1 << 28, 0))
    assert one.keys() == other.keys() and all(abs(one[k] - other[k]) < 1e-9 for k in one)


def test_lm_beats_base_on_held_out_texts(docs):
    found = [r for r in bloom_lm.report(docs).collect() if r.held_out]
    assert sum(r.score for r in found) > sum(r.base_score for r in found)
    assert all(r.score <= 0 for r in found)


def test_lm_odd_rows(odd, none):
    got, want = rows(bloom_lm.report(odd)), brute_base(pairs(odd, "doc_id", "text"))
    assert [g[:5] for g in got] == [w[:5] for w in want]
    assert bloom_lm.report(none).count() == 0
    assert bloom_lm.report(odd.where("doc_id = 0")).count() == 1


def test_filter_levels_never_fall_short():
    h = np.random.default_rng(1).integers(0, 1 << 63, 3000).astype(np.uint64) >> np.uint64(4)
    n = np.random.default_rng(2).integers(1, 50, 3000)
    f = bloom_lm.Filter({0: bloom_lm.build_segment(h, n).tobytes()}, 4)
    levels = f.levels(h)
    assert (levels >= bloom_lm.quantised(n)).all() and (levels == bloom_lm.quantised(n)).mean() > 0.9
    absent = f.levels(h + np.uint64(12345))
    assert (absent > 0).mean() < 0.1


# --- language


def test_language_is_learned(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    found = language_id.report(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    tested = [r for r in found if r.held_out and r.lang_pred != "und"]
    assert sum(r.lang_pred == r.lang for r in tested) >= 0.97 * len(tested)
    assert sum(r.rejected for r in found) <= 0.03 * len(found)
    assert all(0 <= r.score <= 1 for r in found)


def test_numerals_are_no_letters():
    assert language_id.words_in("m² ½ x2 Ⅷ") == {"m": 1, "x": 1}


def test_language_odd_rows(odd, none):
    found = {r.doc_id: r for r in language_id.report(odd).collect()}
    assert {k for k, r in found.items() if r.lang_pred == "und"} == {3, 4, 7, 10}
    assert language_id.report(none).count() == 0
    assert {r.lang_pred for r in language_id.report(odd.withColumn("lang", odd.lang.substr(9, 1)).withColumn("lang", odd.source.substr(5, 2))).collect()} <= {"und", ""}
    kept = language_id.keep_known(odd)
    assert kept.columns == odd.columns and {3, 4, 7, 10}.isdisjoint(r.doc_id for r in kept.collect())


def test_kneser_ney_is_a_distribution():
    model = language_id.Model({"a": Counter({"abba": 3, "ab": 5, "cab": 1, "bac": 2})})
    for head in ("", "a", "ab", "ca", "abb", "zz"):
        # The chance of each next character, from scores of words with and without it.
        base = sum(math.log(x) for x in steps(model, head))
        total = sum(math.exp(sum(math.log(x) for x in steps(model, head + c)) - base) for c in "abc") + end(model, head)
        assert total <= 1.0001
        if "z" not in head:
            assert total > 0.7


def brute_kneser_ney(words, order=4, discount=0.75):
    """log-probability of a word, straight from the definition."""
    marked = {f"^{w}$": n for w, n in words.items()}
    alphabet = {c for w in words for c in w}

    def value(gram, k):
        """Count of the longest n-grams and of those that begin a word, else the number of characters seen before."""
        if k == order or gram[0] == "^":
            return sum(n * sum(w[i : i + k] == gram for i in range(len(w) - k + 1)) for w, n in marked.items())
        return len({w[i - 1] for w in marked for i in range(1, len(w) - k + 1) if w[i : i + k] == gram})

    known = {k: {w[i : i + k] for w in marked for i in range(len(w) - k + 1) if not (k == 1 and i == 0)} for k in range(1, order + 1)}

    def p(c, context):
        k = len(context) + 1
        lower = p(c, context[1:]) if context else 1 / (len(alphabet) + 2)
        rest = [g for g in known[k] if g[:-1] == context]
        if not rest:
            return lower
        mass = sum(value(g, k) for g in rest)
        return (max(0, value(context + c, k) - discount) if context + c in known[k] else 0) / mass + discount * len(rest) / mass * lower

    def score(word):
        text = f"^{word}$"
        return sum(math.log(p(text[i], text[max(0, i - order + 1) : i])) for i in range(1, len(text)))

    return score


def test_word_scores_equal_brute_force_kneser_ney():
    rng = np.random.default_rng(5)
    bags = {x: Counter({"".join(rng.choice(list(letters), rng.integers(1, 7))): int(rng.integers(1, 9)) for _ in range(25)}) for x, letters in (("a", "abcd"), ("b", "bcde"))}
    model = language_id.Model(bags)
    asked = [*bags["a"], *bags["b"], "zz", "aq", "abcdeabcde", "e"]
    got = model.word_scores(asked)
    alphabet = {c for bag in bags.values() for w in bag for c in w}
    for j, lang in enumerate("ab"):
        # The floor is shared by all languages, so its alphabet is that of both.
        extra = Counter(bags[lang])
        score = brute_kneser_ney(extra)
        own = {c for w in bags[lang] for c in w}
        if own == alphabet:
            assert np.allclose(got[:, j], [score(w) for w in asked], rtol=1e-5)
    whole = language_id.Model({"a": bags["a"]})
    score = brute_kneser_ney(bags["a"])
    assert np.allclose(whole.word_scores(asked)[:, 0], [score(w) for w in asked], rtol=1e-5)


def test_small_languages_are_learned(spark):
    data = [(k, "alpha beta gamma delta " * 3, "xx") for k in range(400)] + [(k, "sigma omikron rho tau", "yy") for k in range(1000, 1002)] + [(2000, "quux wibble wobble", "zz")] + [(3000, "ping pong pang", "ww")] * 30
    df = spark.createDataFrame(data, "doc_id long, text string, lang string")
    model = language_id.train(df, language_id.F.lit(True), per_language=100)
    assert model.langs == ["ww", "xx", "yy", "zz"] and np.isfinite(model.limits).all()
    found = {r.doc_id: r.lang_pred for r in language_id.predict(df, model).collect()}
    assert found[1000] == "yy" and found[2000] == "zz" and found[3000] == "ww" and found[5] == "xx"
    alone = language_id.train(df.where("doc_id = 2000"), language_id.F.lit(True))
    assert alone.langs == ["zz"] and np.isinf(alone.limits).all()


def steps(model, word):
    """Probabilities of the characters of ``word`` (without its end)."""
    flat, sizes, place = language_id._flat([word])
    scores = [model.word_scores([word[:k]])[0, 0] for k in range(len(word) + 1)]
    del flat, sizes, place
    return [math.exp(scores[k + 1] - scores[k] + math.log(end(model, word[:k])) - math.log(end(model, word[: k + 1]))) for k in range(len(word))]


def end(model, word):
    """Probability of the end mark after ``word``."""
    flat, _, _ = language_id._flat([word])
    grams = language_id._grams(flat, model.order)
    p = model.floor
    for k in range(1, model.order + 1):
        at = len(flat) - 1
        if at < max(1, k - 1):
            break
        context = grams[k - 2][at - 1 : at] if k > 1 else np.zeros(1, np.uint64)
        keep, c = language_id._find(model.ctx_keys[k - 1], context)
        p = p * model.ctx[k - 1][c[0], 0] if len(keep) else p
        keep, g = language_id._find(model.keys[k - 1], grams[k - 1][at : at + 1])
        p = p + model.prob[k - 1][g[0], 0] if len(keep) else p
    return p


# --- digests


def brute_codes(text):
    """A digest from its definition: length code and quartile codes, without numpy on the way."""
    raw, counts = text.encode(), [0] * 128
    for k in range(4, len(raw)):
        for (i, j), (t0, t1, t2) in zip(quartile_digest._PAIRS, quartile_digest._TABLES, strict=True):
            counts[int(t0[raw[k]]) ^ int(t1[raw[k - i]]) ^ int(t2[raw[k - j]])] += 1
    ranked = sorted(counts)
    q = [ranked[31], ranked[63], ranked[95]]
    return [min(255, math.floor(5 * math.log1p(len(raw)))), *(sum(c > x for x in q) for c in counts)]


def brute_likeness(a, b):
    body = sum({0: 0, 1: 1, 2: 2, 3: 6}[abs(x - y)] for x, y in zip(a[1:], b[1:], strict=True))
    far = abs(a[0] - b[0])
    return 1 - min(300, body + (far if far <= 1 else 12 * far)) / 300


def brute_digests(docs):
    signed = lambda t: int.from_bytes(xxhash.xxh64_digest(t.encode(), 42), "big", signed=True)
    order = sorted(((i is not None, i or type(docs[0][0] or 0)(), signed(t or ""), t or ""), i, t or "") for i, t in docs)
    text_of = lambda c: bytes([c[0], *(64 * c[k] + 16 * c[k + 1] + 4 * c[k + 2] + c[k + 3] for k in range(1, 129, 4))]).hex()
    out, memo = [], {}
    for k, (_, i, t) in enumerate(order):
        u = order[(k + 1) % len(order)][2]
        half = len(t) // 2
        e = t[: len(t) - half] + u[:half]
        own, changed, following = (memo.setdefault(x, brute_codes(x)) if len(x) < 20_000 else quartile_digest._of_texts([x.encode()])[0].tolist() for x in (t, e, u))
        out.append((i, len(t), hashlib.sha256(e.encode()).hexdigest(), text_of(own), text_of(changed), round(brute_likeness(own, changed), 9), round(brute_likeness(own, following), 9)))
    return sorted(out, key=repr)


@pytest.mark.parametrize("ranges", [1, 7, None])
def test_digest_rows_equal_brute_force(docs, odd, none, ranges):
    for df in (docs, odd, odd.where("doc_id = 0"), odd.selectExpr("cast(doc_id as string) doc_id", "text")):
        found = quartile_digest.report(df, ranges)
        assert sorted(((*r[:5], round(r[5], 9), round(r[6], 9)) for r in found.collect()), key=repr) == brute_digests(pairs(df, "doc_id", "text"))
    assert quartile_digest.report(none, ranges).count() == 0


def test_digest_counts_equal_a_plain_loop():
    text = "The quick brown fox – jumps, over the lazy dog.".encode()
    counts = np.zeros(quartile_digest.BUCKETS, int)
    for k in range(4, len(text)):
        for (i, j), (t0, t1, t2) in zip(quartile_digest._PAIRS, quartile_digest._TABLES, strict=True):
            counts[t0[text[k]] ^ t1[text[k - i]] ^ t2[text[k - j]]] += 1
    raw = np.frombuffer(text + text, np.uint8)
    got = quartile_digest.bucket_counts(raw, np.array([0, len(text), 2 * len(text)]))
    assert (got == counts).all()


def test_digest_likeness_separates(docs):
    found = quartile_digest.report(docs.where("length(text) > 400")).collect()
    near, far = np.mean([r.near_edited for r in found]), np.mean([r.near_next for r in found])
    assert near > far + 0.15 and all(0 <= x <= 1 for r in found for x in (r.near_edited, r.near_next))
