"""Language identification as a mixture: each document's language shares by expectation-maximisation.

Languages are hashed character-trigram distributions.  A document's trigrams are drawn from a mixture of them; its
shares are found by expectation-maximisation, and the set of languages by penalised likelihood: sets of the one, two and
three largest shares, and on while a larger one is better, are compared by log-likelihood less half a logarithm of the
number of trigrams for each language.  The largest share within the chosen set is the prediction.

The distributions are fitted on a hash sample of about ``SAMPLE`` documents of each language; all rows are predicted.
Defined results: a null text, one without letters, or an empty fit gives ``und`` with score 0; ties go to the
language that sorts first; other columns are never read.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrowmap import map_texts
from .wordbytes import chunks

SAMPLE = 1500
MOST_LANGUAGES = 500
BITS = 15
STEPS = 8
SMOOTHING = 0.02  # share of the corpus's distribution in each language's
TRIED_SETS = 3  # sizes up to which sets are tried in any case; beyond, while they gain
LEAST_SHARE = 0.02
UNKNOWN = "und"

_letters: np.ndarray | None = None


def letters() -> np.ndarray:
    """Which code points of the basic plane are letters."""
    global _letters
    if _letters is None:
        _letters = np.fromiter((chr(i).isalpha() for i in range(0x10000)), bool, 0x10000)
    return _letters


def trigrams(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Bucket and count of each text's different trigrams, the first of each text, and whether it has a letter."""
    parts = [np.frombuffer((t.lower() if t else "").encode("utf-32-le", "surrogatepass"), np.uint32) for t in texts]
    sizes = np.array([len(p) + 2 for p in parts])
    code = np.full(int(sizes.sum()), 32, np.uint32)
    begin = np.concatenate(([0], np.cumsum(sizes)))
    for p, b in zip(parts, begin):
        code[b + 1 : b + 1 + len(p)] = p
    good = letters()[np.minimum(code, 0xFFFF)]
    above = np.flatnonzero(code > 0xFFFF)
    if len(above):
        kinds, which = np.unique(code[above], return_inverse=True)
        good[above] = np.array([chr(c).isalpha() for c in kinds.tolist()])[which]
    code = np.where(good, code, 32)
    doc = np.repeat(np.arange(len(parts)), sizes)
    keep = good | np.concatenate(([True], good[:-1]))  # of a run of others, the first
    keep[begin[:-1]] = True  # a run ends where its text does
    code, doc, good = code[keep].astype(np.uint64), doc[keep], good[keep]
    has = np.bincount(doc[good], minlength=len(parts)) > 0
    if len(code) < 3:
        return np.empty(0, np.int64), np.empty(0), np.zeros(len(parts) + 1, np.int64), has
    h = (code[:-2] * np.uint64(0x9E3779B97F4A7C15) ^ code[1:-1]) * np.uint64(0xBF58476D1CE4E5B9) ^ code[2:]
    h = (h * np.uint64(0x94D049BB133111EB)) >> np.uint64(64 - BITS)
    ok = (doc[:-2] == doc[2:]) & good[1:-1]
    key, count = np.unique((doc[:-2][ok] << BITS) + h[ok].astype(np.int64), return_counts=True)
    return key & ((1 << BITS) - 1), count.astype(float), np.searchsorted(key >> BITS, np.arange(len(parts) + 1)), has


class LanguageModel:
    def __init__(self, languages: list[str], counts: np.ndarray):
        """``counts``: trigrams by language and bucket."""
        self.languages = languages
        corpus = (counts.sum(0) + 0.1) / (counts.sum() + 0.1 * counts.shape[1])
        own = counts / np.maximum(1.0, counts.sum(1, keepdims=True))
        self.p = ((1 - SMOOTHING) * own + SMOOTHING * corpus).T if len(languages) else np.empty((1 << BITS, 0))

    @classmethod
    def fit(cls, rows: list[tuple[str, str]]) -> LanguageModel:
        names = sorted({lang for _, lang in rows})
        counts = np.zeros((len(names), 1 << BITS))
        texts, langs = [t for t, _ in rows], [names.index(lang) for _, lang in rows]
        for lo, hi in chunks(texts):
            bucket, count, first, _ = trigrams(texts[lo:hi])
            which = np.repeat(langs[lo:hi], np.diff(first))
            np.add.at(counts, (which, bucket), count)
        return cls(names, counts)

    def _maximise(self, p: np.ndarray, count: np.ndarray, first: np.ndarray, share: np.ndarray, steps: int) -> tuple[np.ndarray, np.ndarray]:
        """Shares after so many steps, and the log-likelihood by document; no document is empty."""
        doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
        total = np.add.reduceat(count, first[:-1])[:, None]
        for _ in range(steps):
            r = share[doc] * p
            share = np.add.reduceat(r * (count / r.sum(1))[:, None], first[:-1], axis=0) / total
        return share, np.add.reduceat(count * np.log((share[doc] * p).sum(1)), first[:-1])

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float], np.ndarray]:
        """Language, score and shares (within the chosen set) of every text."""
        k = len(self.languages)
        shares = np.zeros((len(texts), k))
        names, scores = [UNKNOWN] * len(texts), [0.0] * len(texts)
        bucket, count, first, has = trigrams(texts)
        live = np.flatnonzero(np.diff(first) > 0)
        if not k or not len(live):
            return names, scores, shares
        starts = np.concatenate((first[live], first[-1:]))
        p = self.p[bucket]
        n = np.add.reduceat(count, starts[:-1])
        full, _ = self._maximise(p, count, starts, np.full((len(live), k), 1 / k), STEPS)
        order = np.argsort(-full, axis=1, kind="stable")
        rank = np.argsort(order, axis=1, kind="stable")
        logs = np.add.reduceat(count[:, None] * np.log(p), starts[:-1], axis=0)
        best = logs[np.arange(len(live)), order[:, 0]]
        chosen = (rank == 0).astype(float)
        open_ = np.flatnonzero(full[np.arange(len(live)), order[:, min(1, k - 1)]] >= LEAST_SHARE) if k > 1 else np.empty(0, int)
        sizes = np.diff(starts)
        for size in range(2, k + 1):
            if not len(open_):
                break
            at = np.concatenate([np.arange(starts[i], starts[i] + sizes[i]) for i in open_])
            own = np.concatenate(([0], np.cumsum(sizes[open_])))
            start = np.where(rank[open_] < size, full[open_], 0)
            share, like = self._maximise(p[at], count[at], own, start / start.sum(1, keepdims=True), STEPS)
            better = like - (size - 1) / 2 * np.log(n[open_] + 1) > best[open_]
            best[open_[better]] = (like - (size - 1) / 2 * np.log(n[open_] + 1))[better]
            chosen[open_[better]] = share[better]
            if size >= TRIED_SETS:
                open_ = open_[better]
        shares[live] = chosen
        top = chosen.argmax(1)
        for i, t, s in zip(live.tolist(), top.tolist(), full[np.arange(len(live)), top].tolist()):
            if has[i]:
                names[i], scores[i] = self.languages[t], min(1.0, max(0.0, s))
        return names, scores, shares


def training_rows(docs: DataFrame, sample: int = SAMPLE, key: str = "doc_id", text: str = "text", lang: str = "lang", learnable: Column | None = None) -> list[tuple[str, str]]:
    """About ``sample`` texts of each language, by hash of their id."""
    known = docs.where(learnable if learnable is not None else F.lit(True)).where(F.col(lang).isNotNull() & F.col(text).isNotNull())
    counts = {r[0]: r[1] for r in known.groupBy(lang).count().limit(MOST_LANGUAGES + 1).collect()}
    if len(counts) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    share = F.create_map(*[F.lit(x) for k, n in counts.items() for x in (k, min(1.0, sample / n))]) if counts else None
    if share is None:
        return []
    drawn = F.pmod(F.xxhash64(key, F.lit(5)), F.lit(1 << 30)) < share[F.col(lang)] * (1 << 30)
    return [(r[0], r[1]) for r in known.where(drawn).select(text, lang, key).orderBy(key).select(text, lang).collect()]


def fit(docs: DataFrame, sample: int = SAMPLE) -> LanguageModel:
    """Fitted on documents whose crc32 of the id as text is not 2 modulo 4."""
    return LanguageModel.fit(training_rows(docs, sample, learnable=F.crc32(F.col("doc_id").cast("string")) % 4 != 2))


def identify(docs: DataFrame, model: LanguageModel, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key``, ``lang_pred``, ``score`` and ``shares`` (language to share, of the chosen set) of every row."""
    src = docs.select(F.col(key), F.col(text))
    sent = docs.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([src.schema.fields[0], T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("shares", T.MapType(T.StringType(), T.DoubleType(), False))])

    def make(cols: list[list]) -> dict[str, list]:
        names, scores, shares = sent.value.predict(cols[1])
        maps: list[list[tuple[str, float]]] = [[] for _ in names]
        for i, j in np.argwhere(shares > 0).tolist():
            maps[i].append((sent.value.languages[j], float(shares[i, j])))
        return {key: cols[0], "lang_pred": names, "score": scores, "shares": maps}

    return map_texts(src, 1, schema, make)
