"""The near-dedup stage against brute force over all pairs."""

import re
from collections import Counter
from itertools import combinations

import numpy as np

import corpus_pipeline
from textgroups.llm import near_copies

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def plain_set(text):
    w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def kept_ids(texts):
    sets, parent = {i: plain_set(t) for i, t in texts.items()}, {i: i for i in texts}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in combinations(sets, 2):
        shared, all_ = len(sets[a] & sets[b]), len(sets[a] | sets[b])
        if 10 * shared >= 8 * all_:
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    return Counter(i for i in sets if root(i) == i)


#: Tables enough for a pair at 0.8 to be a candidate for certain (a miss of 1 in 10^5), so that all else can be held to equality.
CERTAIN = 64


def stage(spark, texts, tables=CERTAIN):
    d = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    return Counter(r["doc_id"] for r in near_copies.keep_one(d, tables).collect())


def test_production_parameters(spark, small):
    """The pipeline's stage: no clean text goes, and at least 0.95 of what brute force drops goes, at 0.8 to 1."""
    rng = np.random.default_rng(9)
    rows = [r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()]
    texts = dict(enumerate(rows))
    for t in rows:
        w = t.split(" ")
        if len(w) >= 60:
            for share in (0.005, 0.01, 0.015, 0.02):
                v = list(w)
                for at in rng.choice(len(v), max(1, int(share * len(v))), replace=False):
                    v[at] = f"changed{at}"
                texts[len(texts)] = " ".join(v)
    d = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    kept = {r["doc_id"] for r in dict(corpus_pipeline.STAGES)["simhash near-dedup"](spark, d, "").collect()}
    right = set(kept_ids(texts))
    assert right <= kept
    assert len(kept - right) <= 0.05 * (len(texts) - len(right))


def test_stage_equals_brute_force(spark, small):
    rng = np.random.default_rng(5)
    rows = [r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()]
    texts = dict(enumerate([*rows, "", None, "one", "ONE", "one two"]))
    for t in rows[:60]:
        w = t.split(" ")
        for changes in (1, 2, 4):
            v = list(w)
            for at in rng.integers(len(v), size=max(1, changes * len(v) // 100)):
                v[at] = f"changed{at}"
            texts[len(texts)] = " ".join(v)
    assert stage(spark, texts) == kept_ids(texts)


def test_large_group_and_common_passage(spark):
    """Buckets beyond their limit: copies of one text at many distances, chains of edits, texts around one passage."""
    rng = np.random.default_rng(6)
    base = [f"w{i}" for i in rng.integers(0, 5000, 200)]
    texts = {}
    for n in range(120):
        v = list(base)
        for at in rng.integers(200, size=n % 7):
            v[at] = f"x{n}-{at}"
        texts[n] = " ".join(v)
    chain = [f"c{i}" for i in range(200)]
    for n in range(60):
        chain[3 * n] = f"d{n}"
        texts[500 + n] = " ".join(chain)
    for n in range(60):
        texts[900 + n] = " ".join([*base[:150], *(f"y{n}-{i}" for i in range(60 if n % 2 else 20))])
    assert stage(spark, texts) == kept_ids(texts)


def test_repeated_ids_over_different_texts(spark):
    texts = ["alpha beta gamma delta epsilon zeta", "one two three four five six seven", "one two three four five six seven"]
    d = spark.createDataFrame([(1, texts[0]), (1, texts[1]), (2, texts[2])], "doc_id long, text string")
    assert sorted(r["text"] for r in near_copies.keep_one(d).collect()) == sorted(texts[:2])
