"""Language identification with interpolated Kneser-Ney character models.

For each language one model of character 1- to 4-grams inside words (a start mark, the letters, an end
mark).  All languages share one sorted array of n-gram hashes per order; beside it lie, per language, the
discounted probability of the n-gram and, for contexts, the weight that goes to the shorter context.  A text's
score is the cross-entropy per character; the lowest wins, and a text whose lowest value lies above what
its language shows on held-out training texts is rejected.

Training takes a bounded sample: about ``PER_LANGUAGE`` labelled documents of each language, those with the
smallest hash of doc_id and text.  A fifth of them, never the one with the smallest hash of all, calibrates rejection; where a
language has no such documents (it may have a single one), it is rejected beyond the highest limit of the others, or
never if there is none.  Prediction reads whole texts and sees the text alone.

Edge cases: every language with a labelled text is learned; null texts and texts without a letter are ``und`` with score 0 and rejected; ties go to the language
first in order; without training rows everything is ``und``; repeated rows are judged alike.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import mix, opened, sent

ORDER = 4
PER_LANGUAGE = 1500
DISCOUNT = 0.75
#: Of the training documents, each of which the hash says so is kept to calibrate rejection.
CALIBRATION_SHARE = 5
QUANTILE = 0.995
SLACK = 1.25
#: Hashes are drawn from so many that the share of a sample stays exact in any number of documents.
LOTS = 1 << 48
CACHE = 200_000
UNKNOWN = "und"

_LETTERS = re.compile(r"[^\W\d_]+")
_START, _END = 2, 3
_P = np.uint64(0x9E3779B97F4A7C15)


def words_in(text: str | None) -> Counter:
    found = Counter(_LETTERS.findall(text.lower())) if text else Counter()
    # The pattern lets through numerals that are no digits (superscripts, fractions); those are no letters.
    for word in [w for w in found if not w.isalpha()]:
        n = found.pop(word)
        for part in "".join(c if c.isalpha() else " " for c in word).split():
            found[part] += n
    return found


def _flat(words: list[str]):
    """Code points of marked words one after another, and the position of each within its word."""
    flat = np.frombuffer("".join(f"\x02{w}\x03" for w in words).encode("utf-32-le", "surrogatepass"), np.uint32)
    sizes = np.array([len(w) + 2 for w in words], np.int64)
    starts = np.cumsum(sizes) - sizes
    place = np.arange(len(flat)) - np.repeat(starts, sizes)
    return flat, sizes, place


def _grams(flat: np.ndarray, order: int) -> list[np.ndarray]:
    """Hash of the k-gram that ends at each position, k = 1 .. order (only valid where the word is long enough)."""
    out, h = [], np.zeros(len(flat), np.uint64)
    scale = np.uint64(1)
    for k in range(order):
        back = np.zeros(len(flat), np.uint64)
        back[k:] = flat[: len(flat) - k] if k else flat
        h = h + back.astype(np.uint64) * scale
        with np.errstate(over="ignore"):
            scale = scale * _P
        out.append(mix(h + np.uint64(k + 1)))
    return out


class Model:
    """Sorted hash arrays of all languages; see the module's text."""

    def __init__(self, counts: dict[str, Counter], order: int = ORDER, discount: float = DISCOUNT):
        self.langs, self.order = sorted(counts), order
        self.limits = np.full(len(self.langs), np.inf)
        per = [self._one(counts[x], order, discount) for x in self.langs]
        self.keys, self.prob, self.ctx_keys, self.ctx = [], [], [], []
        for k in range(order):
            for keys_out, values_out, which, default in ((self.keys, self.prob, 0, 0.0), (self.ctx_keys, self.ctx, 1, 1.0)):
                every = np.unique(np.concatenate([p[k][which][0] for p in per])) if per else np.zeros(0, np.uint64)
                table = np.full((len(every), len(self.langs)), default, np.float32)
                for j, p in enumerate(per):
                    table[np.searchsorted(every, p[k][which][0]), j] = p[k][which][1]
                keys_out.append(every)
                values_out.append(table)
        alphabet = {c for x in counts.values() for w in x for c in w}
        self.floor = 1.0 / (len(alphabet) + 2)

    @staticmethod
    def _one(words: Counter, order: int, discount: float):
        """Per order: ((n-gram hashes, discounted probabilities), (context hashes, weights of the shorter context))."""
        flat, sizes, place = _flat(list(words))
        weight = np.repeat(np.array(list(words.values()), np.float64), sizes)
        grams = _grams(flat, order + 1)
        out = []
        for k in range(1, order + 1):
            # The longest n-grams, and those that begin a word, count by frequency; the others by how many
            # different characters come before them.
            at = np.flatnonzero((place >= k) | (place == k - 1) & (k > 1))
            own = grams[k - 1][at]
            context = grams[k - 2][at - 1] if k > 1 else np.zeros(len(at), np.uint64)
            keys, first, back = np.unique(own, return_index=True, return_inverse=True)
            total = np.bincount(back, weight[at], len(keys))
            if k < order:
                longer = np.flatnonzero(place >= k)
                _, one = np.unique(grams[k][longer], return_index=True)
                kinds = np.bincount(np.searchsorted(keys, grams[k - 1][longer[one]]), minlength=len(keys)).astype(np.float64)
                starts = place[at[first]] == k - 1
                value = np.where(starts & (k > 1), total, np.maximum(kinds, 1.0))
            else:
                value = total
            ctx_of = context[first]
            ctx_keys, ctx_back = np.unique(ctx_of, return_inverse=True)
            mass = np.bincount(ctx_back, value, len(ctx_keys))
            kinds = np.bincount(ctx_back, minlength=len(ctx_keys))
            out.append(((keys, (value - discount).clip(0) / mass[ctx_back]), (ctx_keys, discount * kinds / mass)))
        return out

    def word_scores(self, words: list[str]) -> np.ndarray:
        """(words, languages) log-probabilities, natural logarithm."""
        flat, sizes, place = _flat(words)
        grams = _grams(flat, self.order)
        p = np.full((len(flat), len(self.langs)), self.floor)
        for k in range(1, self.order + 1):
            at = np.flatnonzero(place >= max(1, k - 1))
            context = grams[k - 2][at - 1] if k > 1 else np.zeros(len(at), np.uint64)
            keep, c = _find(self.ctx_keys[k - 1], context)
            p[at[keep]] *= self.ctx[k - 1][c]
            keep, g = _find(self.keys[k - 1], grams[k - 1][at])
            p[at[keep]] += self.prob[k - 1][g]
        logs = np.log(p)
        logs[place == 0] = 0
        return np.add.reduceat(logs, np.cumsum(sizes) - sizes, axis=0) if len(words) else np.zeros((0, len(self.langs)))


def _find(keys: np.ndarray, wanted: np.ndarray):
    """(which of ``wanted`` are among the sorted ``keys``, and where)."""
    if not len(keys):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    keep = np.flatnonzero(keys[at] == wanted)
    return keep, at[keep]


class Scorer:
    """Cross-entropies of texts; scores of words are remembered."""

    def __init__(self, model: Model):
        self.model, self.place = model, {}
        self.table = np.zeros((CACHE, max(1, len(model.langs))))

    def entropies(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """(texts, languages) cross-entropy per character in nats, and the number of characters (0: no letter)."""
        bags = [words_in(t) for t in texts]
        out, sizes = np.zeros((len(bags), len(self.model.langs))), np.zeros(len(bags))
        a = 0
        while a < len(bags):  # in portions whose words fit the memory of scores
            new: dict[str, None] = {}
            b = a
            while b < len(bags) and len(new) < CACHE // 4:
                new.update(dict.fromkeys(w for w in bags[b] if w not in self.place))
                b += 1
            words = list(new)
            if len(self.place) + len(words) > len(self.table):
                self.place = {}
                words = list(dict.fromkeys(w for bag in bags[a:b] for w in bag))
                if len(words) > len(self.table):
                    self.table = np.zeros((2 * len(words), self.table.shape[1]))
            start = len(self.place)
            for x in range(0, len(words), 20_000):
                part = words[x : x + 20_000]
                self.table[start + x : start + x + len(part)] = self.model.word_scores(part)
            self.place.update(zip(words, range(start, start + len(words)), strict=True))
            for k in range(a, b):
                if bag := bags[k]:
                    n = np.fromiter(bag.values(), np.float64, len(bag))
                    at = np.fromiter((self.place[w] for w in bag), np.int64, len(bag))
                    sizes[k] = sum((len(w) + 1) * c for w, c in bag.items())
                    out[k] = -(n @ self.table[at]) / sizes[k]
            a = b
        return out, sizes


def sample(docs: DataFrame, training: F.Column, per_language: int = PER_LANGUAGE) -> DataFrame:
    """About ``per_language`` training rows of each language, with ``part``: 1 where kept for calibration.

    The share to take follows from the number of labelled rows of the language; a hash of doc_id and text decides, and the
    rows with the smallest hash are always taken, for training.
    """
    lot = F.pmod(F.xxhash64(F.lit("sample"), "doc_id", "text"), F.lit(LOTS))
    labelled = docs.where(training & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("lang", "text", "doc_id", lot.alias("lot"))
    sizes = labelled.groupBy("lang").agg(F.count("*").alias("n"), F.min("lot").alias("low")).collect()
    share, low = F.lit(None).cast("double"), F.lit(None).cast("long")
    for r in sizes:
        share = F.when(F.col("lang") == r["lang"], float(LOTS) * per_language / r["n"]).otherwise(share)
        low = F.when(F.col("lang") == r["lang"], F.lit(r["low"])).otherwise(low)
    part = (F.pmod(F.xxhash64(F.lit("part"), "doc_id", "text"), F.lit(CALIBRATION_SHARE)) == 0) & (F.col("lot") > low)
    return labelled.where((F.col("lot") < share) | (F.col("lot") == low)).select("lang", "text", part.cast("int").alias("part"))


def train(docs: DataFrame, training: F.Column, per_language: int = PER_LANGUAGE, order: int = ORDER) -> Model:
    """Fit models and rejection limits; words are counted on the executors."""

    def count(batches):
        bags: dict[str, Counter] = {}
        for batch in batches:
            for lang, text, part in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                if not part:
                    bags.setdefault(lang, Counter()).update(words_in(text))
        rows = [(x, w, n) for x, bag in bags.items() for w, n in bag.items()]
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], ["lang", "word", "n"])

    chosen = sample(docs, training, per_language)
    table = chosen.mapInArrow(count, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n")).toArrow()
    bags: dict[str, Counter] = {}
    for lang, word, n in zip(*(table.column(k).to_pylist() for k in range(3)), strict=True):
        bags.setdefault(lang, Counter())[word] = n
    model = Model(bags, order)
    shared = sent(docs, model)

    def calibrate(batches):
        scorer = Scorer(opened(Model, shared))
        names = {x: k for k, x in enumerate(scorer.model.langs)}
        for batch in batches:
            rows = [r for r in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True) if r[2] and r[0] in names]
            values, sizes = scorer.entropies([t for _, t, _ in rows])
            kept = [(x, float(v[names[x]])) for (x, _, _), v, n in zip(rows, values, sizes, strict=True) if n]
            if kept:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*kept, strict=True)], ["lang", "entropy"])

    limits = chosen.mapInArrow(calibrate, "lang string, entropy double").groupBy("lang").agg(F.percentile("entropy", QUANTILE).alias("q")).collect()
    if limits:
        model.limits[:] = SLACK * max(r["q"] for r in limits)
    for r in limits:
        model.limits[model.langs.index(r["lang"])] = SLACK * r["q"]
    shared.unpersist()
    return model


def predict(docs: DataFrame, model: Model, keep_columns: bool = False) -> DataFrame:
    """doc_id (or all columns), lang_pred, score, entropy, rejected."""
    shared = sent(docs, model)
    base = docs if keep_columns else docs.select("doc_id", "text")
    kept = [c for c in base.columns if keep_columns or c != "text"]
    added = [("lang_pred", T.StringType()), ("score", T.DoubleType()), ("entropy", T.DoubleType()), ("rejected", T.BooleanType())]
    clash = {n for n, _ in added} & set(kept)
    kept = [c for c in kept if c not in clash]
    schema = T.StructType([*(base.schema[c] for c in kept), *(T.StructField(n, t) for n, t in added)])

    def run(batches):
        scorer = Scorer(opened(Model, shared))
        langs = [*scorer.model.langs, UNKNOWN]
        limits = np.append(scorer.model.limits, 0)
        for batch in batches:
            names = batch.schema.names
            for a in range(0, batch.num_rows, 500):
                part = batch.slice(a, 500)
                values, sizes = scorer.entropies(part.column(names.index("text")).to_pylist())
                known = (sizes > 0) & (values.shape[1] > 0)
                best, score, lowest = judge(values, sizes, known)
                best = np.where(known, best, len(langs) - 1)
                yield pa.RecordBatch.from_arrays(
                    [
                        *(part.column(names.index(c)) for c in kept),
                        pa.array([langs[k] for k in best], pa.string()),
                        pa.array(np.where(known, score, 0.0)),
                        pa.array(np.where(known, lowest, 0.0)),
                        pa.array(~known | (lowest > limits[best])),
                    ],
                    schema.fieldNames(),
                )

    return base.mapInArrow(run, schema)


def judge(values: np.ndarray, sizes: np.ndarray, known: np.ndarray):
    """(best language, its share of the likelihood with at most 50 characters' evidence, its cross-entropy)."""
    if not values.shape[1] or not len(values):
        return np.zeros(len(values), np.int64), np.zeros(len(values)), np.zeros(len(values))
    best = values.argmin(axis=1)
    lowest = values[np.arange(len(values)), best]
    odds = np.exp(-(values - lowest[:, None]) * np.minimum(sizes, 50)[:, None])
    return best, 1 / odds.sum(axis=1), lowest


def held_out(modulus: int = 3, rest: int = 1) -> F.Column:
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(modulus)) == rest


def report(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected."""
    model = train(docs, ~held_out())
    return predict(docs, model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "rejected")


def keep_known(docs: DataFrame) -> DataFrame:
    """The documents whose language is recognised, all columns as they were."""
    shared = sent(docs, train(docs, ~held_out()))

    def run(batches):
        scorer = Scorer(opened(Model, shared))
        limits = scorer.model.limits
        for batch in batches:
            at = batch.schema.names.index("text")
            for a in range(0, batch.num_rows, 500):
                part = batch.slice(a, 500)
                values, sizes = scorer.entropies(part.column(at).to_pylist())
                known = (sizes > 0) & (values.shape[1] > 0)
                best, _, lowest = judge(values, sizes, known)
                good = known & (lowest <= limits[best]) if len(limits) else known
                yield part.filter(pa.array(good))

    return docs.mapInArrow(run, docs.schema)
