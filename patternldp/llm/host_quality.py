"""Quality rules judged per document and per host.

Each document gets rule counts from its whole text.  Rule failures are summed by host, each host's failure
rate is shrunk towards the corpus with a beta prior fitted to the hosts (method of moments), and a host whose shrunk rate
stands out from the prior's mean by a stated margin is rejected; the verdict is joined back to its documents.
Hosts that fail about as often as the corpus are all kept, whatever that rate is.

Defined results: a null or empty text has no words, so it fails the base rule; a null host is one host of its own;
repeated rows are judged each; an empty table gives an empty result; other columns are never looked at.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrowmap import map_texts
from .scratch import materialise
from .wordbytes import split, windows

SYMBOLS = "#*$%&|<>"
MIN_WORDS = 10
REPEAT_PERCENT = 20
WINDOW = 5
#: A host is rejected if a rule's shrunk rate, less so many posterior deviations, is above the prior's mean by more than this.
MARGIN, DEVIATIONS = 0.2, 2.0
#: Rejected hosts that may be broadcast; beyond it the verdicts are joined by a shuffle.
BROADCAST_HOSTS = 100_000
#: Hosts with at least this share of all documents are joined by broadcast: there are at most its inverse.
HOT_SHARE = 0.001

_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in SYMBOLS]] = True
_SPACE_CHARS = " \t\n\x0b\x0c\r"
_COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")
RULES = ("few_words", "repeated", "symbols", "dup_lines")


def text_counts(texts: list[str | None]) -> dict[str, list[int]]:
    """Rule counts of each text: words, their code points, symbols, repeated lines, words in repeated windows, lines with a word."""
    words = split(texts)
    blob = words.blob
    space = (blob == 32) | ((blob >= 9) & (blob <= 13))
    chars = words.per_text(((blob & 0xC0) != 0x80) & ~space)
    symbols = words.per_text(_SYMBOL[blob])
    h, first = windows(words, WINDOW)
    repeats, dup_lines, n_lines = [], [], []
    for i, t in enumerate(texts):
        own = h[first[i] : first[i + 1]]
        s = np.sort(own)
        twice = s[1:][s[1:] == s[:-1]]
        if len(twice):
            twice = twice[np.concatenate(([True], twice[1:] != twice[:-1]))]
            pos = np.minimum(np.searchsorted(twice, own), len(twice) - 1)
            edge = np.zeros(len(own) + WINDOW, np.int64)
            at = np.flatnonzero(twice[pos] == own)
            np.add.at(edge, at, 1)
            np.add.at(edge, at + WINDOW, -1)
            repeats.append(int((np.cumsum(edge) > 0).sum()))
        else:
            repeats.append(0)
        lines = [x for x in t.split("\n") if x.strip(_SPACE_CHARS)] if t else []
        n_lines.append(len(lines))
        dup_lines.append(len(lines) - len(set(lines)))
    return dict(zip(_COUNTS, (words.count.tolist(), chars.tolist(), symbols.tolist(), dup_lines, repeats, n_lines)))


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"))


def _failures() -> dict[str, Column]:
    return {
        "few_words": F.col("n_words") < MIN_WORDS,
        "repeated": 100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"),
        "symbols": F.col("n_symbols") > F.col("n_words"),
        "dup_lines": 2 * F.col("n_dup_lines") > F.col("n_lines"),
    }


def measure(docs: DataFrame, key: list[str], text: str, host: str) -> DataFrame:
    """``key`` columns, ``host`` and the counts, one row per document."""
    src = docs.select(*[F.col(k).alias(f"_k{i}") for i, k in enumerate(key)], F.col(host).alias("_host"), F.col(text).alias("_text"))
    names = src.columns[:-1]
    schema = T.StructType([*src.schema.fields[:-1], *[T.StructField(c, T.LongType()) for c in _COUNTS]])
    return map_texts(src, len(names), schema, lambda cols: dict(zip(names, cols)) | text_counts(cols[-1]))


def host_verdicts(counts: DataFrame, margin: float = MARGIN) -> DataFrame:
    """One row per host: documents, shrunk failure rate of each rule and whether one of them stands out by ``margin``.

    Prior by moments over hosts: with mean m and variance v of the raw rates, less the variance m(1-m) mean(1/documents) that
    alike hosts show by chance, strength s = m(1-m)/v - 1, kept within 1 and 1e6; the shrunk rate is
    (failures + m s) / (documents + s).
    """
    hosts = counts.groupBy(F.col("_host")).agg(F.count("*").alias("n_docs"), *[F.sum(c.cast("long")).alias(f"f_{r}") for r, c in _failures().items()])
    rates = {r: F.col(f"f_{r}") / F.col("n_docs") for r in RULES}
    prior = hosts.agg(*[x for r, c in rates.items() for x in (F.avg(c).alias(f"m_{r}"), F.var_pop(c).alias(f"v_{r}"))], F.avg(1 / F.col("n_docs")).alias("chance"))
    out = hosts.crossJoin(F.broadcast(prior))  # a prior of one row
    for r in RULES:
        m, v = F.col(f"m_{r}"), F.col(f"v_{r}")
        s = F.greatest(F.lit(1.0), F.least(F.lit(1e6), m * (1 - m) / F.greatest(v - m * (1 - m) * F.col("chance"), F.lit(1e-12)) - 1))
        out = out.withColumn(f"rate_{r}", (F.col(f"f_{r}") + m * s) / (F.col("n_docs") + s))
        rate = F.col(f"rate_{r}")
        out = out.withColumn(f"over_{r}", rate - DEVIATIONS * F.sqrt(rate * (1 - rate) / (F.col("n_docs") + s + 1)) - m)
    over = F.greatest(*[F.col(f"over_{r}") for r in RULES])
    return out.select("_host", "n_docs", *[f"rate_{r}" for r in RULES], (over > margin).alias("host_rejected"))


def _join_verdicts(counts: DataFrame, verdicts: DataFrame) -> DataFrame:
    """``counts`` with ``host_rejected``; hot hosts never meet in one task."""
    rejected = verdicts.where("host_rejected").select("_host", "n_docs")
    if rejected.limit(BROADCAST_HOSTS + 1).count() <= BROADCAST_HOSTS:
        return counts.join(F.broadcast(rejected.select(F.col("_host").alias("_h"), F.lit(True).alias("_r"))), F.col("_host").eqNullSafe(F.col("_h")), "left").withColumn("host_rejected", F.coalesce("_r", F.lit(False))).drop("_h", "_r")
    total = counts.count()
    hot = verdicts.where(F.col("n_docs") >= HOT_SHARE * total).select(F.col("_host").alias("_h"), F.col("host_rejected").alias("_hot"))
    cold = rejected.where(F.col("n_docs") < HOT_SHARE * total).select(F.col("_host").alias("_h"), F.lit(True).alias("_r"))
    with_hot = counts.join(F.broadcast(hot), F.col("_host").eqNullSafe(F.col("_h")), "left").drop("_h")
    settled = with_hot.where("_hot is not null").withColumnRenamed("_hot", "host_rejected")
    rest = with_hot.where("_hot is null").drop("_hot").join(cold, F.col("_host").eqNullSafe(F.col("_h")), "left").withColumn("host_rejected", F.coalesce("_r", F.lit(False))).drop("_h", "_r")
    return settled.unionByName(rest)


def host_quality(docs: DataFrame, key: str = "doc_id", text: str = "text", host: str = "source", margin: float = MARGIN) -> DataFrame:
    """The key, the host, all counts, ``base_failed``, ``host_rejected`` and ``kept`` of every document."""
    counts = materialise(measure(docs, [key], text, host), "host-quality")
    judged = _join_verdicts(counts, host_verdicts(counts, margin))
    return judged.select(
        F.col("_k0").alias(key), F.col("_host").alias(host), *_COUNTS, base_failed().alias("base_failed"), "host_rejected",
        (~base_failed() & ~F.col("host_rejected")).alias("kept"),
    )


def keep_good(docs: DataFrame, text: str = "text", host: str = "source", margin: float = MARGIN) -> DataFrame:
    """The rows of ``docs`` that pass, all columns as they were.

    Texts are counted twice instead of being shuffled: once for the hosts, once more beside the rows that are kept.
    """
    counts = materialise(measure(docs, [], text, host), "host-quality")
    verdicts = host_verdicts(counts, margin)
    names = docs.columns
    at, where = names.index(text), names.index(host)
    schema = T.StructType([*[T.StructField(f"_c{i}", f.dataType) for i, f in enumerate(docs.schema)], T.StructField("_host", docs.schema[where].dataType)])

    def passing(cols: list[list]) -> dict[str, list]:
        c = text_counts(cols[at])
        good = [i for i, (n, r) in enumerate(zip(c["n_words"], c["n_repeat_words"])) if n >= MIN_WORDS and 100 * r <= REPEAT_PERCENT * n]
        out = {f"_c{k}": [col[i] for i in good] for k, col in enumerate(cols)}
        return out | {"_host": out[f"_c{where}"]}

    passed = map_texts(docs.toDF(*[f"_c{i}" for i in range(len(names))]), at, schema, passing)
    return _join_verdicts(passed, verdicts).where("not host_rejected").select(*[F.col(f"_c{i}").alias(n) for i, n in enumerate(names)])
