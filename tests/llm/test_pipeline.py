import re
from collections import Counter

import pytest
import corpus_pipeline
from patternldp.llm import toxicity
from patternldp.llm.oracles import ORACLES
from patternldp.llm.queries import QUERIES


def rows(df):
    df = df[sorted(df.columns)]
    return sorted(map(repr, df.astype(object).where(df.notna(), None).itertuples(index=False, name=None)))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_queries_match_sql(name, spark, sf, duck):
    assert rows(QUERIES[name](spark, sf).toPandas()) == rows(duck.sql(ORACLES[name]).df())


def test_pipeline(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert 4 <= len(corpus_pipeline.STAGES) <= 5
    at = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, at, sf)
        assert got.columns == docs.columns and got.count() <= at.count()
        at = got
    packed = corpus_pipeline.run(spark, sf).toPandas()
    assert set(packed["doc_id"]) == {r["doc_id"] for r in at.collect()}
    assert packed.groupby("sequence_id")["length"].sum().max() <= 2048


def brute_quality(docs):
    """Base rules by counting words one by one; no host stands out in the given tables."""
    kept = set()
    for r in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", r["text"] or "")
        grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        twice = Counter(grams)
        covered = {i + j for i, g in enumerate(grams) if twice[g] > 1 for j in range(5)}
        if len(w) >= 10 and 100 * len(covered) <= 20 * len(w):
            kept.add(r["doc_id"])
    return kept


def brute_firsts(docs):
    """The documents without a smaller one in their class, all pairs compared."""
    sets = {}
    for r in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), r["text"] or ""))
        sets[r["doc_id"]] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    label = {i: i for i in sets}
    ids = sorted(sets)
    for n, i in enumerate(ids):
        for j in ids[n + 1 :]:
            a, b = sets[i], sets[j]
            if a and b and 100 * min(len(a), len(b)) >= 80 * max(len(a), len(b)):
                c = len(a & b)
                if 100 * c >= 80 * (len(a) + len(b) - c) and label[i] != label[j]:
                    low, high = sorted((label[i], label[j]))
                    label = {k: low if v == high else v for k, v in label.items()}
    return {i for i in sets if label[i] == i}


def test_stages_by_brute_force(spark, sf):
    """Each filter over all rows of a table against the same rule in plain Python."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = docs.collect()
    stages = dict(corpus_pipeline.STAGES)
    good = stages["quality rules"](spark, docs, sf)
    assert {r["doc_id"] for r in good.collect()} == brute_quality(rows)
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    model = toxicity.fit(docs, labels)
    clean = {r["doc_id"] for r in stages["toxicity"](spark, docs, sf).collect()}
    assert clean == {r["doc_id"] for r in rows if model.score([r["text"]])[0] < toxicity.CUTOFF}
    assert {r["doc_id"] for r in stages["n-gram Jaccard join"](spark, docs, sf).collect()} == brute_firsts(rows)
