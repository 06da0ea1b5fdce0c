"""Convolutional toxicity classifier in numpy: hashed word embeddings, filters of several widths, max pooling.

A word is known by the hashes of itself and of its prefixes of four to eight bytes.  Its embedding is the sum of the learned
rows of these hashes, from a random start, beside the shrunk log-odds of each hash in the rows that are learned from.  While
training, a document's own words are taken out of its log-odds, so that rare words do not look decisive, and half of the
words are left out at random.  Filters of width 1, 2 and 3 run over the words, each keeps its largest response in the whole
text, and a logistic layer scores them; filters and layer start at random, and the weights of the later epochs are averaged.

A fifth of the rows of either label takes no part in the training: thresholds are set on it, by language, and drawn towards the
threshold of all languages, and that towards even odds, the fewer rows there are.  The language is guessed from the text's
function words, and scores are shifted so that every threshold lies at 0.7.

The model is fitted on at most ``SAMPLE`` labelled documents of either label, drawn by hash; all else covers all
rows.  Defined results: a null or empty text has no response and gets the score of none; rows of one id are scored each;
without labels of both kinds every score is 0; other columns are never read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrowmap import map_texts, released
from .scratch import release_memory
from .wordbytes import chunks, mix, word_hashes

SAMPLE = 2500
CUTOFF = 0.7
BITS, LEARNED_BITS, LEARNED = 17, 14, 16
PREFIXES = (4, 5, 6, 7, 8)
FIXED = 1 + len(PREFIXES)
WIDTHS = {1: 8, 2: 4, 3: 4}
BATCH, RATE, TABLE_RATE, PENALTY, LEFT_OUT = 16, 0.01, 0.05, 1e-3, 0.5
STEPS, EPOCHS = 800, (5, 40)  # epochs make about so many steps, within these bounds
SHRINK = 1.5  # documents that the log-odds of a word are shrunk by
ODDS_SCALE = 0.3
CALIBRATION, PRIOR = 5, 20  # a row in five; rows that a threshold is shrunk by

# Common function words of the languages that thresholds are kept for.
FUNCTION_WORDS = {
    "en": "the of and to in is that it for was with as be this are from",
    "de": "der die und das nicht von den mit ist des im dem sich ein auf für",
    "fr": "le la les de et des un une du est que pour dans qui au par",
    "es": "el la los de y que en un se por con las para una su del",
}

_LETTER = np.full(256, 32, np.uint8)
_LETTER[128:] = np.arange(128, 256)
_LETTER[97:123] = np.arange(97, 123)
_LETTER[65:91] = np.arange(97, 123)


def _function_table() -> tuple[np.ndarray, np.ndarray]:
    words, rows = {}, []
    for at, lang in enumerate(FUNCTION_WORDS):
        for w in FUNCTION_WORDS[lang].split():
            h = int(word_hashes(np.frombuffer(w.encode(), np.uint8))[0][0])
            words.setdefault(h, np.zeros(len(FUNCTION_WORDS)))[at] = 1
    keys = np.array(sorted(words), np.uint64)
    rows = np.array([words[int(k)] for k in keys])
    return keys, rows


def featurise(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Buckets of every word (the word and its prefixes), each text's first word, and its guessed language.

    A word is a run of letters of the lower-cased text; bytes above 127 count as letters.
    """
    enc = [t.lower().encode("utf-8", "surrogatepass") if t else b"" for t in texts]
    begin = np.zeros(len(enc) + 1, np.int64)
    np.cumsum([len(e) + 1 for e in enc], out=begin[1:])
    blob = _LETTER[np.frombuffer(b" ".join(enc) + b" " * (max(PREFIXES) + 1), np.uint8)]
    h, start = word_hashes(blob)
    first = np.searchsorted(start, begin)
    buckets = np.empty((len(h), FIXED), np.int32)
    buckets[:, 0] = (h >> np.uint64(64 - BITS)).astype(np.int32)
    p, alive = np.zeros(len(h), np.uint64), np.ones(len(h), bool)
    for j in range(max(PREFIXES)):
        b = blob[start + j]
        alive &= b != 32
        p = p * np.uint64(257) + np.where(alive, b, 0).astype(np.uint64)
        if j + 1 in PREFIXES:
            buckets[:, 1 + PREFIXES.index(j + 1)] = (mix(p + np.uint64(j)) >> np.uint64(64 - BITS)).astype(np.int32)
    keys, rows = _function_table()
    at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
    hit = np.where((keys[at] == h)[:, None], rows[at], 0)
    total = np.zeros((len(h) + 1, rows.shape[1]))
    np.cumsum(hit, axis=0, out=total[1:])
    by_text = total[first[1:]] - total[first[:-1]]
    lang = np.where(by_text.max(1) > 0, by_text.argmax(1), -1)
    return buckets, first, lang


class Vocabulary:
    """Numbers for words that differ in a bucket, so that a document to learn from is four bytes a word."""

    def __init__(self) -> None:
        self.number: dict[bytes, int] = {}

    def ids(self, buckets: np.ndarray) -> np.ndarray:
        if not len(buckets):
            return np.empty(0, np.int32)
        own, inverse = np.unique(np.ascontiguousarray(buckets).view(f"V{buckets.itemsize * FIXED}").ravel(), return_inverse=True)
        return np.array([self.number.setdefault(w.tobytes(), len(self.number)) for w in own], np.int32)[inverse]

    def rows(self) -> np.ndarray:
        return np.frombuffer(b"".join(self.number), np.int32).reshape(-1, FIXED)


class ToxicityModel:
    """Fitted weights; small arrays only, so that it can be sent to every worker."""

    def __init__(self) -> None:
        rng = np.random.default_rng(7)
        d = FIXED + LEARNED
        self.odds = np.zeros((FIXED, 1 << BITS), np.float32)
        self.weights = {"table": (rng.standard_normal((FIXED << LEARNED_BITS, LEARNED)) * 0.3).astype(np.float32), "bias": np.zeros(1, np.float32)}
        for w, n in WIDTHS.items():
            self.weights[f"filter{w}"] = (rng.standard_normal((w, d, n)) / np.sqrt(d * w)).astype(np.float32)
            self.weights[f"shift{w}"] = np.zeros(n, np.float32)
        self.weights["out"] = (rng.standard_normal(sum(WIDTHS.values())) * 0.3).astype(np.float32)
        self.limits = np.zeros(len(FUNCTION_WORDS) + 1)  # the last is for other languages
        self.fitted = False

    def embed(self, buckets: np.ndarray) -> np.ndarray:
        x = np.zeros((len(buckets), FIXED + LEARNED), np.float32)
        for f in range(FIXED):
            x[:, f] = self.odds[f, buckets[:, f]]
            x[:, FIXED:] += self.weights["table"][_slot(buckets[:, f], f)]
        return x

    def _log_odds(self, pos: np.ndarray, neg: np.ndarray) -> np.ndarray:
        p1 = self.n[1] / (self.n[0] + self.n[1])
        return ODDS_SCALE * (np.log((pos + SHRINK * p1) / (neg + SHRINK * (1 - p1))) + np.log((1 - p1) / p1))

    def _without(self, b: np.ndarray, f: int, label: int) -> np.ndarray:
        pos, neg = self.seen[f][1][b].astype(float), self.seen[f][0][b].astype(float)
        return self._log_odds(np.maximum(pos - label, 0), np.maximum(neg - (1 - label), 0))

    def respond(self, x: np.ndarray, w: int) -> np.ndarray:
        n = len(x) - w + 1
        return sum(x[j : n + j] @ self.weights[f"filter{w}"][j] for j in range(w)) + self.weights[f"shift{w}"] if n > 0 else np.empty((0, WIDTHS[w]), np.float32)

    def logits(self, buckets: np.ndarray, first: np.ndarray) -> np.ndarray:
        """One number per text, before calibration."""
        x = self.embed(buckets)
        count = np.diff(first)
        parts = []
        for w, n in WIDTHS.items():
            best = np.zeros((len(count), n), np.float32)
            r = self.respond(x, w)
            ok = count >= w
            if ok.any():
                for j in range(1, w):  # windows that reach into the next text
                    at = first[1:] - j
                    r[at[(at >= first[:-1]) & (at < len(r))]] = -np.inf
                starts = first[:-1][ok]
                best[ok] = np.maximum(np.maximum.reduceat(r, starts, axis=0), 0)
            parts.append(best)
        return np.concatenate(parts, 1) @ self.weights["out"] + self.weights["bias"][0]

    def fit(self, texts: list[str], labels: list[int], train: bool = True) -> ToxicityModel:
        """``train=False`` leaves filters, layer and learned rows at their random start, for comparison."""
        y = np.array(labels, np.int64)
        if len(np.unique(y)) < 2:
            return self
        vocabulary, docs, langs = Vocabulary(), [], []
        for lo, hi in chunks(texts):
            b, first, lang = featurise(texts[lo:hi])
            ids = vocabulary.ids(b)
            docs += [ids[first[i] : first[i + 1]].copy() for i in range(hi - lo)]
            langs.append(lang)
        langs = np.concatenate(langs)
        rows = vocabulary.rows()
        del vocabulary
        aside = np.zeros(len(y), bool)
        rng = np.random.default_rng(11)
        for label in (0, 1):
            own = rng.permutation(np.flatnonzero(y == label))
            aside[own[: len(own) // CALIBRATION]] = True
        self.n = np.bincount(y[~aside], minlength=2).astype(float)
        self.seen = np.zeros((FIXED, 2, 1 << BITS), np.float32)
        for i in np.flatnonzero(~aside):
            own = rows[np.unique(docs[i])]
            for f in range(FIXED):
                self.seen[f, y[i], np.unique(own[:, f])] += 1
        self.odds = np.stack([self._log_odds(s[1], s[0]) for s in self.seen]).astype(np.float32)
        if train:
            # Own words are taken out by label alone, so a word has two rows of fixed numbers, whatever the documents.
            self.fixed = [np.stack([self._without(rows[:, f], f, label) for f in range(FIXED)], 1).astype(np.float32) for label in (0, 1)]
            self.slots = np.stack([_slot(rows[:, f], f) for f in range(FIXED)], 1)
            self._train(docs, y, np.flatnonzero(~aside), rng)
            del self.fixed, self.slots
        del self.seen
        scores = np.array([self.logits(rows[docs[i]], np.array([0, len(docs[i])]))[0] for i in np.flatnonzero(aside)])
        known, langs = y[aside], langs[aside]
        everywhere = _limit(scores, known, 0.0)
        for at in range(-1, len(FUNCTION_WORDS)):
            self.limits[at] = _limit(scores[langs == at], known[langs == at], everywhere)
        self.fitted = True
        return self

    def _forward(self, words: np.ndarray, label: int):
        x = np.concatenate((self.fixed[label][words], self.weights["table"][self.slots[words]].sum(1)), 1)
        pooled, where = [], {}
        for w, n in WIDTHS.items():
            r = self.respond(x, w)
            if len(r):
                where[w] = r.argmax(0)
                pooled.append(np.maximum(r[where[w], np.arange(n)], 0))
            else:
                pooled.append(np.zeros(n, np.float32))
        h = np.concatenate(pooled)
        return float(h @ self.weights["out"] + self.weights["bias"][0]), h, where, x

    def _train(self, docs: list[np.ndarray], y: np.ndarray, rows: np.ndarray, rng: np.random.Generator) -> None:
        table = self.weights["table"]
        dense = {k: v for k, v in self.weights.items() if k != "table"}
        moment = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in dense.items()}
        spread = np.zeros(len(table), np.float32)
        heavy = min(4.0, self.n[0] / self.n[1])
        epochs = min(max(-(-STEPS * BATCH // len(rows)), EPOCHS[0]), EPOCHS[1])
        mean: dict[str, np.ndarray] = {}
        step = 0
        for epoch in range(epochs):
            order = rng.permutation(rows)
            for lo in range(0, len(order), BATCH):
                batch = order[lo : lo + BATCH]
                grad = {k: np.zeros_like(v) for k, v in dense.items()}
                touched, pulls = [], []
                for i in batch:
                    words = docs[i][rng.random(len(docs[i])) >= LEFT_OUT]
                    z, h, where, x = self._forward(words, y[i])
                    g = (1 / (1 + np.exp(-z)) - y[i]) * (heavy if y[i] else 1.0) / len(batch)
                    grad["out"] += g * h
                    grad["bias"] += g
                    at = 0
                    for w, n in WIDTHS.items():
                        if w in where:
                            live = g * dense["out"][at : at + n] * (h[at : at + n] > 0)
                            grad[f"shift{w}"] += live
                            for j in range(w):
                                p = where[w] + j
                                grad[f"filter{w}"][j] += x[p].T * live
                                touched.append(self.slots[words[p]].ravel())
                                pulls.append(np.repeat(live[:, None] * dense[f"filter{w}"][j][FIXED:].T, FIXED, axis=0))
                        at += n
                step += 1
                for k, v in dense.items():
                    m, s = moment[k]
                    g = grad[k] + (0 if k == "bias" else PENALTY) * v
                    m += 0.1 * (g - m)
                    s += 0.01 * (g * g - s)
                    v -= RATE * (m / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.99**step)) + 1e-6)
                if touched:
                    slots, at_slot = np.unique(np.concatenate(touched), return_inverse=True)
                    total = np.zeros((len(slots), LEARNED), np.float32)
                    np.add.at(total, at_slot, np.concatenate(pulls))
                    spread[slots] += (total * total).mean(1)
                    table[slots] -= TABLE_RATE * total / (np.sqrt(spread[slots])[:, None] + 1e-6)
            late = epoch - epochs // 2
            if late >= 0:
                for k, v in self.weights.items():
                    mean[k] = v.copy() if late == 0 else mean[k] + (v - mean[k]) / (late + 1)
        self.weights = mean

    def score(self, texts: list[str | None]) -> np.ndarray:
        if not self.fitted:
            return np.zeros(len(texts))
        b, first, lang = featurise(texts)
        z = self.logits(b, first) - self.limits[lang] + np.log(CUTOFF / (1 - CUTOFF))
        return 1 / (1 + np.exp(-np.clip(z.astype(float), -40, 40)))


def _slot(bucket: np.ndarray, f: int) -> np.ndarray:
    """The learned row of a bucket of feature ``f``."""
    return (bucket >> (BITS - LEARNED_BITS)) + (f << LEARNED_BITS)


def _limit(scores: np.ndarray, y: np.ndarray, base: float) -> float:
    """The threshold with the best balanced accuracy, in the middle of its gap, drawn towards ``base`` where rows are few."""
    rarer = min((y == 0).sum(), (y == 1).sum())
    if not rarer:
        return base
    order = np.argsort(scores, kind="stable")
    s, label = scores[order], y[order]
    below = np.concatenate(([0], np.cumsum(label == 0))) / (label == 0).sum()
    above = 1 - np.concatenate(([0], np.cumsum(label == 1))) / (label == 1).sum()
    edges = np.concatenate(([s[0] - 2], (s[1:] + s[:-1]) / 2, [s[-1] + 2]))
    ok = np.concatenate(([True], s[1:] > s[:-1], [True]))
    best = edges[np.argmax(np.where(ok, below + above, -1))]
    return float(base + (best - base) * rarer / (rarer + PRIOR))


def training_rows(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, key: str = "doc_id", text: str = "text", label: str = "toxic", learnable: Column | None = None) -> list[tuple[str, int]]:
    """At most ``sample`` texts of either label, by hash of their id; ids in ``labels`` that ``learnable`` holds for."""
    known = labels.where(learnable if learnable is not None else F.lit(True)).where(F.col(key).isNotNull() & F.col(label).isin(0, 1)).groupBy(F.col(key).alias("_id")).agg(F.max(label).cast("int").alias("_y"))
    by_hash = [F.xxhash64("_id"), F.col("_id")]
    picked = known.where("_y = 1").orderBy(*by_hash).limit(sample).union(known.where("_y = 0").orderBy(*by_hash).limit(sample))
    rows = docs.select(F.col(key).alias("_id"), F.col(text).alias("_text")).join(F.broadcast(picked), "_id").collect()
    unique = {r["_id"]: (r["_text"] or "", r["_y"]) for r in sorted(rows, key=lambda r: (r["_id"], r["_text"] or ""))}
    return list(unique.values())


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> ToxicityModel:
    """Fitted on labelled rows whose crc32 of the id as text is not 1 modulo 3."""
    rows = training_rows(docs, labels, sample, learnable=F.crc32(F.col("doc_id").cast("string")) % 3 != 1)
    model = ToxicityModel().fit([t for t, _ in rows], [y for _, y in rows])
    del rows
    release_memory()
    return model


def toxicity(docs: DataFrame, model: ToxicityModel, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key`` and ``score`` of every row."""
    src = docs.select(F.col(key), F.col(text))
    sent = docs.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([src.schema.fields[0], T.StructField("score", T.DoubleType())])
    return map_texts(src, 1, schema, lambda cols: {key: cols[0], "score": sent.value.score(cols[1]).tolist()})


def keep_clean(docs: DataFrame, labels: DataFrame, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that score below the cutoff, all columns as they were."""
    sent = docs.sparkSession.sparkContext.broadcast(fit(docs, labels))
    at = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(at).to_pylist()
            keep = np.concatenate([sent.value.score(texts[lo:hi]) < CUTOFF for lo, hi in chunks(texts)] or [np.empty(0, bool)])
            yield batch.filter(pa.array(keep))

    names = [f"_c{i}" for i in range(len(docs.columns))]
    plain = docs.toDF(*names)
    return plain.mapInArrow(released(run), plain.schema).toDF(*docs.columns)
