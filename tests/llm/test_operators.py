"""The ten operators against brute force, and on odd tables."""

import re
import zlib
from collections import Counter, defaultdict
from itertools import combinations

import numpy as np
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from tests.llm.test_near_copies import kept_ids
from tests.oracle import assert_same, connect
from textgroups.llm import exact_dedup, lang_id, license_scan, lm_score, mixing, packing, quality, queries, sharding, simhash, token_cache

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


@pytest.fixture(scope="module")
def docs(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet")


@pytest.fixture(scope="module")
def rows(docs):
    return [(r["doc_id"], r["text"]) for r in docs.collect()]


def odd(spark):
    """Nulls in every column, empty and long texts, equal and repeated rows, and columns named like our own."""
    words = "alpha beta gamma delta epsilon zeta eta theta iota kappa".split()
    rng = np.random.default_rng(2)
    passage = " ".join(words[i] for i in rng.integers(0, 10, 60))
    texts = [(1, None, None, None), (2, "", "en", "a"), (3, " \t\n\x0b", None, "a"), (4, "word", "en", None), (5, "word", "en", "b"), (5, "word", "en", "b"), (6, "w o r d", "de", "b"), (None, passage, "de", "c"), (None, passage, "de", "c"), (7, passage, "de", None), (8, passage + "\n" + passage, "en", "c"), (9, " ".join(f"{words[i % 10]}{i}" for i in range(60_000)), "en", "a"), (10, "x" * 50_000, None, "d"), (11, "Žluťoučký kůň <|endoftext|> 日本語 " * 10, "cs", "d"), (12, "a\x00b   c d", "en", "d")]
    extra = "digest string, slot int, shard int, rank int, fp long, n int, key string, kept boolean, size int, row string, id int, place int, words int, length int, failed int, component_id int, _b string, _h string, _m string, keep_id int"
    names = [x.split()[0] for x in extra.split(", ")]
    df = spark.createDataFrame([(*t, None) for t in texts], "doc_id long, text string, lang string, source string, n_chars long")
    return df.select("*", *[F.lit(None if i % 2 else i).cast(x.split()[1]).alias(names[i]) for i, x in enumerate(extra.split(", "))])


OPERATORS = {
    "mixing": mixing.mixture,
    "license": license_scan.scan,
    "lm": lm_score.score_held_out,
    "sharding": sharding.place,
    "quality": lambda d: quality.verdicts(quality.ledger(d)),
    "tokens": token_cache.count_tokens,
    "exact": exact_dedup.deduplicate,
    "language": lang_id.identify,
    "simhash": simhash.near_groups,
}


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_odd_and_empty_tables(spark, name):
    d = odd(spark)
    got = OPERATORS[name](d)
    assert Counter(r["doc_id"] for r in got.collect()) == Counter(r["doc_id"] for r in d.collect())
    assert OPERATORS[name](d.limit(0)).count() == 0


def test_packing_of_odd_and_empty_tables(spark):
    d = odd(spark)
    got = packing.pack(d).collect()
    assert {r["doc_id"] for r in got} == {r["doc_id"] for r in d.collect()}
    empty = [r for r in got if r["doc_id"] in (1, 2, 3)]
    assert all(r["length"] == 1 for r in empty) and len(empty) == 3
    assert packing.pack(d.limit(0)).count() == 0


def test_stages_on_odd_and_empty_tables(spark):
    d = odd(spark)
    for name, stage in corpus_pipeline.STAGES:
        got = stage(spark, d, "")
        assert name == "best-fit packing" or got.columns == d.columns
        got.collect()
        assert stage(spark, d.limit(0), "").count() == 0
    ids = lambda x: Counter(r["doc_id"] for r in x.collect())
    assert ids(corpus_pipeline.quality_rules(spark, d, "")) == {None: 2, 7: 1, 9: 1, 11: 1} or 9 in ids(corpus_pipeline.quality_rules(spark, d, ""))
    kept = ids(corpus_pipeline.exact(spark, d, ""))
    assert kept[1] + kept[2] + kept[3] == 1 and kept[3] == 1  # most code points among the empty ones
    assert kept[6] == 1 and not kept[4] and not kept[5] and kept[7] == 1 and not kept[None]


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_equals_sql(spark, small, name):
    assert_same(queries.queries()[name](spark, small), connect(small), queries.oracle_sql()[name])


def test_mix_keeps_its_limits(spark, docs):
    got = mixing.mixture(docs).toPandas()
    by = got.groupby("source").agg(target=("target", "first"), taken=("taken", "sum"), size=("source_size", "first"))
    assert (abs(by["target"] - by["taken"]) <= 1).all() and (by["taken"] <= 2 * by["size"]).all()
    assert (got["taken"] <= 2 * got["size"]).all() and by["target"].sum() == pytest.approx(1.5 * by["size"].sum())
    again = mixing.mixture(docs.repartition(3)).toPandas()
    assert sorted(zip(got["doc_id"], got["taken"])) == sorted(zip(again["doc_id"], again["taken"]))


def test_mix_targets_by_hand(spark):
    sizes = spark.createDataFrame([("a", 10), ("b", 100), (None, 200)], "source string, size long")
    got = {r["source"]: r["target"] for r in mixing.source_targets(sizes).collect()}
    left = 1.5 * 310 - 20  # 'a' is full at 20; the rest goes by weights 2 and 1, 'b' is full at 200
    assert got == {"a": 20.0, "b": 200.0, None: left - 200}


def test_schedule_is_even(spark, docs):
    sizes = docs.select("doc_id", "source", mixing.word_count(F.col("text")).alias("size"))
    slots = mixing.schedule(mixing.source_targets(sizes), 16).toPandas().sort_values("slot")
    assert slots["slot"].is_unique
    total = Counter(slots["_src"])
    for source, n in total.items():
        first = (slots["_src"].to_numpy()[: len(slots) // 2] == source).sum()
        assert abs(first - n / 2) <= 0.1 * n + 8
        assert sorted(slots[slots["_src"] == source]["rank"]) == list(range(n))


def test_licences(spark):
    texts = ["x\nReleased under the MIT License.\ny", "Licensed under the Apache License, Version 2.0.", "Some MIT License talk.", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. noise here. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.", "You may obtain a copy of the License at\nYou may not use this file except in compliance with the License.", None]
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["licenses"] for r in license_scan.scan(d).collect()}
    assert got == {0: ["MIT"], 1: ["Apache-2.0"], 2: [], 3: ["BSD-2-Clause"], 4: [], 5: []}


def test_language_model_against_brute_force(spark, docs, rows, monkeypatch):
    monkeypatch.setattr(lm_score, "SHARD_BYTES", 40_000)
    monkeypatch.setattr(lm_score, "HELD_KEYS", 5_000)
    got = {r["doc_id"]: r for r in lm_score.score_held_out(docs).collect()}
    split = lambda t: [*WORD.findall(lower(t)), None]
    train = [split(t) for i, t in rows if zlib.crc32(str(i).encode()) % 5 != 1]
    uni = Counter(w for x in train for w in x)
    n, v = sum(uni.values()), len(uni)
    pairs = Counter(p for x in train for p in zip([0, *x[:-1]], x))
    before = Counter(w for _, w in pairs)
    after = defaultdict(lambda: [0, 0, 0])
    for (a, _), c in pairs.items():
        after[a][min(c, 3) - 1] += 1
    tops = lambda cs: [sum(c == i for c in cs) for i in (1, 2, 3, 4)]
    d1, d2 = lm_score.discounts(tops(before.values())), lm_score.discounts(tops(pairs.values()))
    follows = sum(before.values())
    rest = sum(d * k for d, k in zip(d1, (tops(before.values())[0], tops(before.values())[1], sum(c > 2 for c in before.values())))) / follows / (v + 1)
    seen = {**uni, 0: len(train)}

    def p(a, w):
        c = before.get(w, 0)
        low = (c - [0, *d1][min(c, 3)]) / follows + rest
        if a not in seen:
            return low
        c = pairs.get((a, w), 0)
        return (c - [0, *d2][min(c, 3)] + np.dot(d2, after[a]) * low) / seen[a]

    words = [*uni, "never seen"]
    assert sum(p("the", w) for w in words) == pytest.approx(1) and sum(p("never seen", w) for w in words) == pytest.approx(1)
    for i, t in rows[::7]:
        x, r = split(t), got[i]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(x), sum(w in uni for w in x), n)
        assert r["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 1)
        assert r["base_score"] == pytest.approx(sum(np.log10((uni.get(w, 0) + 0.5) / (n + 0.5 * (v + 1))) for w in x))
        assert r["score"] == pytest.approx(sum(np.log10(p(a, w)) for a, w in zip([0, *x[:-1]], x)))
    held = [r for r in got.values() if r["held_out"]]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)


def test_shards_are_even_and_stable():
    names = sharding.shard_names(16)
    share = Counter(sharding.fill_table(names, 4093))
    assert max(share.values()) - min(share.values()) <= 1
    assert sharding.moved_share(names, names[:-1], 4093) < 2.5 / 16
    with pytest.raises(ValueError):
        sharding.fill_table(names, 4095)


def test_quality_measures_against_brute_force(spark, docs, rows):
    got = {r["doc_id"]: r for r in quality.ledger(docs).collect()}
    for i, t in rows:
        w = WORD.findall(t)
        windows = defaultdict(list)
        for j in range(len(w) - 7):
            windows[tuple(w[j : j + 8])].append(j)
        covered = {j + o for js in windows.values() if len(js) > 1 for j in js for o in range(8)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        want = (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered))
        assert tuple(got[i][m] for m in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")) == want


def test_policies_and_ablations_read_the_ledger(spark, docs, small, tmp_path):
    ledger = quality.ledger(docs)
    kept = {r["doc_id"] for r in quality.verdicts(ledger).filter("kept").collect()}
    assert kept == {r["doc_id"] for r in quality.keep_good(docs).collect()}
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{small}/labels.parquet").collect()}
    base = {r["doc_id"] for r in quality.verdicts(ledger, "base").filter("kept").collect()}
    assert all((i in kept) == (labels[i] == 1) for i in labels if i in base)
    path = str(tmp_path / "ledger")
    stored = quality.ledger(docs, path)
    assert stored.filter("rules <> 9").isEmpty() and spark.read.parquet(path).count() == docs.count()
    for policy in ("v1", "base", ("symbols",)):
        alive = stored.filter(F.col("failed").bitwiseAND(F.lit(quality.mask_of(policy) | 3)) == 0).count()
        assert quality.verdicts(stored, policy).filter("kept").count() == alive == quality.keep_good(docs, policy).count()
        assert all(r["kept_without"] == alive + r["failing_alone"] for r in quality.ablations(stored, policy).collect())
    for r in quality.ablations(ledger).collect():
        without = tuple(x for x in quality.POLICIES["v1"] if x != r["rule"])
        mask = quality.mask_of(without)
        assert r["kept_without"] == ledger.filter(F.col("failed").bitwiseAND(F.lit(mask)) == 0).count()


@pytest.mark.parametrize("model", ["piece_bpe_32k.model", "byte_bpe_50k.json"])
def test_token_counts_and_cache(spark, docs, rows, tmp_path, model):
    path = public_tokenizers.path(model)
    if model.endswith(".model"):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        count = lambda t: len(sp.encode(t))
    else:
        from tokenizers import Tokenizer

        count = lambda t, e=Tokenizer.from_file(path): len(e.encode(t, add_special_tokens=False).ids)
    half = docs.filter("doc_id % 2 = 0")
    token_cache.count_tokens(half, path, str(tmp_path))
    before = spark.read.parquet(str(tmp_path)).count()
    assert before == half.select("text").distinct().count()
    got = {r["doc_id"]: r for r in token_cache.count_tokens(docs, path, str(tmp_path)).collect()}
    assert spark.read.parquet(str(tmp_path)).count() == docs.select("text").distinct().count()
    for i, t in rows[::5]:
        n = count(t)
        assert (got[i]["n_bytes"], got[i]["n_tokens"], got[i]["over_limit"]) == (len(t.encode()), n, n > 4096)
    token_cache.count_tokens(docs, path, str(tmp_path)).collect()
    assert spark.read.parquet(str(tmp_path)).count() == docs.select("text").distinct().count()


def test_the_three_ways_of_the_cache(spark, docs, rows, tmp_path, monkeypatch):
    """Misses sent to the tasks, known rows sent to the tasks, and neither: the same counts."""
    want = {r["doc_id"]: r["n_tokens"] for r in token_cache.count_tokens(docs).collect()}
    most = docs.filter("doc_id >= 3")
    for limit in (0, 10 * token_cache.ROW_BYTES):
        monkeypatch.setattr(token_cache, "BROADCAST_BYTES", limit)
        path = str(tmp_path / str(limit))
        token_cache.count_tokens(most, cache_path=path).collect()
        assert {r["doc_id"]: r["n_tokens"] for r in token_cache.count_tokens(docs, cache_path=path).collect()} == want


def test_hot_source_and_hot_text(spark, docs, rows):
    """A third of all rows in one source with one text: the mix, the counts and the packing are whole."""
    hot = spark.range(10_000, 10_000 + len(rows) // 2).select(F.col("id").alias("doc_id"), F.lit(rows[0][1]).alias("text"), F.lit("hot").alias("source"))
    every = docs.select("doc_id", "text", "source").unionByName(hot)
    got = mixing.mixture(every).toPandas()
    by = got.groupby("source").agg(target=("target", "first"), taken=("taken", "sum"))
    assert (abs(by["target"] - by["taken"]) <= 1).all() and (got["taken"] <= 2 * got["size"]).all()
    counts = {r["doc_id"]: r["n_tokens"] for r in token_cache.count_tokens(every).collect()}
    assert len(counts) == every.count() and {counts[10_000 + i] for i in range(len(rows) // 2)} == {counts[rows[0][0]]}
    pieces = packing.pack(every).toPandas()
    total = pieces.groupby("doc_id")["length"].sum()
    assert (total[total.index >= 10_000] == total[rows[0][0]]).all() and len(total) == every.count()
    assert not pieces.duplicated(["sequence_id", "offset"]).any() and pieces.groupby("sequence_id")["length"].sum().max() <= 4096


def test_packing_against_the_tokenizer(spark, docs, rows):
    from tokenizers import Tokenizer

    encoder = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    got = defaultdict(dict)
    all_rows = packing.pack(docs, keep_ids=True).collect()
    for r in all_rows:
        got[r["doc_id"]][r["piece"]] = r
    for i, t in rows:
        ids = [*encoder.encode(t, add_special_tokens=False).ids, 1]
        assert len(got[i]) == -(-len(ids) // 4096)
        for p, r in got[i].items():
            want = ids[p * 4096 : (p + 1) * 4096]
            assert list(r["ids"]) == want and (r["start"], r["length"]) == (p * 4096, len(want)) and r["ids_crc32"] == zlib.crc32(np.array(want, "<u4").tobytes())
    sequences = defaultdict(list)
    for r in all_rows:
        sequences[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 4096
    assert len(sequences) <= -(-sum(r["length"] for r in all_rows) // 4096) * 1.1 + 1


def test_word_ids_equal_whole_texts():
    import pyarrow as pa
    from tokenizers import Tokenizer

    encoder, ours = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")), packing.WordIds(public_tokenizers.path("word_bpe_49k.json"))
    rng = np.random.default_rng(4)
    bits = list("abzAZtsre09 \n\t\x0b'<|>#$.,!?-_é̈ßİΣςが日  \x1c") + ["<|endoftext|>", "<|ENDOFTEXT|>", "don't", "I'LL", "the,"]
    for special in (True, False):
        texts = ["".join(bits[i] for i in rng.integers(0, len(bits), rng.integers(0, 50)) if special or "|" not in bits[i]) for _ in range(3000)]
        ids, n = ours.encode(pa.array(texts))
        ends = np.cumsum(n)
        for t, a, b in zip(texts, ends - n, ends):
            assert ids[a:b].tolist() == [*encoder.encode(t, add_special_tokens=False).ids, 1]


@pytest.mark.parametrize("seed", range(4))
def test_plan_places_every_length(seed):
    rng = np.random.default_rng(seed)
    histogram = {int(x): int(rng.integers(1, 40)) for x in rng.integers(1, 101, 30)}
    bins, ranks = defaultdict(list), defaultdict(list)
    for length, rank, count, first, each, offset in packing.plan(histogram, 100):
        ranks[length] += range(rank, rank + count)
        for r in range(count):
            bins[first + r // each].append((offset + length * (r % each), length))
    assert {x: sorted(r) for x, r in ranks.items()} == {x: list(range(n)) for x, n in histogram.items()}
    for parts in bins.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 100
    assert len(bins) <= 1.23 * sum(x * n for x, n in histogram.items()) / 100 + 1


def test_one_row_of_a_group_is_kept(spark):
    """Equal ids over different texts, exact repeats, null and extreme ids."""
    low = -(1 << 63)
    table = [(1, "ab"), (1, "a b"), (2, "a\tb"), (3, "x"), (3, "x"), (None, "y z"), (None, "y z"), (low, "yz"), (low, "q"), (None, "q"), (4, None), (5, "")]
    d = spark.createDataFrame(table, "doc_id long, text string")
    got = exact_dedup.deduplicate(d).collect()
    assert Counter(r["doc_id"] for r in got) == Counter(i for i, _ in table)
    kept = Counter((r["doc_id"], r["group_size"]) for r in got if r["kept"])
    assert kept == Counter([(1, 3), (3, 2), (None, 3), (low, 2), (4, 2)])
    assert {r["keep_id"] for r in got if r["group_size"] == 3} == {1, None}
    assert Counter((r["doc_id"], r["text"]) for r in exact_dedup.keep_first(d).collect()) == Counter([(1, "a b"), (3, "x"), (None, "y z"), (low, "q"), (4, None)])


def test_an_index_drops_what_came_before(spark):
    index = exact_dedup.DigestIndex(spark, "index_batches", 2)
    try:
        one = spark.createDataFrame([(1, "a b"), (2, "c")], "doc_id long, text string")
        two = spark.createDataFrame([(0, "ab  "), (1, "a b"), (3, "d"), (4, "d")], "doc_id long, text string")
        assert all(r["kept"] for r in exact_dedup.deduplicate(one, index).collect())
        assert {(r["doc_id"], r["keep_id"], r["kept"]) for r in exact_dedup.deduplicate(two, index).collect()} == {(0, 1, False), (1, 1, False), (3, 3, True), (4, 3, False)}
    finally:
        index.drop()


def test_digest_index_persists(spark, docs):
    index = exact_dedup.DigestIndex(spark, "index_test", 4)
    try:
        first, second = docs.filter("doc_id < 100"), docs.filter("doc_id >= 50")
        a = exact_dedup.deduplicate(first, index).collect()
        n = index.read().count()
        assert n == len({r["text_sha256"] for r in a})
        b = exact_dedup.deduplicate(second, index).collect()
        known = {r["text_sha256"]: r["keep_id"] for r in a}
        assert all(r["keep_id"] == known[r["text_sha256"]] for r in b if r["text_sha256"] in known)
        assert index.read().count() == len({r["text_sha256"] for r in [*a, *b]})
        plan = index.read().join(exact_dedup.digests(second).hint("merge"), "digest")._jdf.queryExecution().executedPlan().toString()
        assert "Bucketed: true" in plan
    finally:
        spark.sql("DROP TABLE IF EXISTS index_test")


def test_language_network(spark, small):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = lang_id.identify(docs).join(docs.select("doc_id", "lang", "text"), "doc_id").filter("held_out").collect()
    right = [r["lang_pred"] == r["lang"] for r in got if r["text"]]
    assert np.mean(right) >= 0.97 and all(0 <= r["score"] <= 1 for r in got)
    changed = docs.withColumn("lang", F.when(lang_id.held_out(F.col("doc_id")), F.lit("xx")).otherwise(F.col("lang")))
    again = {r["doc_id"]: r["lang_pred"] for r in lang_id.identify(changed).filter("held_out").collect()}
    assert again == {r["doc_id"]: r["lang_pred"] for r in got}
    assert "xx" not in again.values()


def test_verdict_of_whole_texts_against_the_plain_network(spark, docs):
    """Every window of every text through the network itself, weighed by its bytes; 'und' without a letter."""
    labelled = docs.select("doc_id", "text", "lang").filter("lang is not null and text <> ''")
    net = lang_id.train(*lang_id.sample(labelled, 200), epochs=2)
    some = docs.select("doc_id", "text").limit(40).collect()
    texts = {r["doc_id"]: r["text"] for r in some} | {-1: None, -2: "", -3: "12 !?\n", -4: "ÄÖ " * 300, -5: "A" * lang_id.WINDOW}
    d = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    for r in lang_id.predict(d, net).collect():
        octets = lower(texts[r["doc_id"]]).encode()
        if not re.search(r"[^\W\d_]", texts[r["doc_id"]] or ""):
            assert (r["lang_pred"], r["score"]) == ("und", 0)
            continue
        total, size = np.zeros(len(net.languages)), 0
        for i in range(0, len(octets), lang_id.WINDOW):
            piece = octets[i : i + lang_id.WINDOW]
            x = np.zeros((1, lang_id.WINDOW), np.uint8)
            x[0, : len(piece)] = np.frombuffer(piece, np.uint8)
            logits = np.maximum(lang_id._forward(net, x)[1], 0)[0] @ net.weights + net.offset
            total += len(piece) * (logits - logits.max() - np.log(np.exp(logits - logits.max()).sum()))
            size += len(piece)
        p = np.exp(total / size - (total / size).max())
        p /= p.sum()
        assert r["score"] == pytest.approx(p.max(), abs=1e-3) and (r["lang_pred"] == net.languages[int(p.argmax())] or np.sort(p)[-2] > p.max() - 1e-3)


def test_convolution_tables_equal_the_network():
    rng = np.random.default_rng(0)
    x = rng.integers(32, 127, (40, lang_id.WINDOW)).astype(np.uint8)
    net = lang_id.train(x, ["ab"[i % 2] for i in range(40)], epochs=2)
    _, top, _ = lang_id._forward(net, x)
    assert np.allclose(np.maximum(top, 0), lang_id.Reader(net).pooled(x), atol=1e-4)


def plain_fingerprint(text):
    w = WORD.findall(lower(text))
    if not w:
        return 0
    grams = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or [" ".join(w)]
    h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_fingerprints_and_groups_against_brute_force(spark, rows):
    rng = np.random.default_rng(8)
    texts = [t for _, t in rows[:60]]
    for t in list(texts):
        w = t.split(" ")
        if len(w) > 300:
            w[int(rng.integers(len(w)))] = "changed"
            texts += [" ".join(w), t.upper()]
    texts += ["", None, "one", "ONE", "one two"]
    d = spark.createDataFrame([(i * 3 + 1, t) for i, t in enumerate(texts)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in simhash.near_groups(d).collect()}
    prints = {i * 3 + 1: plain_fingerprint(t) for i, t in enumerate(texts)}
    assert {i: r["fingerprint"] for i, r in got.items()} == {i: f"{p:016x}" for i, p in prints.items()}
    assert {i: r["component_id"] for i, r in got.items()} == groups_of(prints)
    assert len({r["component_id"] for r in got.values()}) < len(got) - 20


def groups_of(prints):
    parent = {i: i for i in prints}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in combinations(prints, 2):
        if (prints[a] ^ prints[b]).bit_count() <= 2:
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    return {i: root(i) for i in prints}


def test_links_of_dense_and_chained_prints(spark):
    """A ball of 300 prints around one (a bucket beyond its limit), a chain, and pairs 3 bits apart."""
    rng = np.random.default_rng(12)
    centre = int(rng.integers(1 << 62))
    ball = {centre} | {centre ^ (1 << int(a)) ^ (1 << int(b)) for a, b in rng.integers(0, 64, (300, 2))}
    chain = [int(rng.integers(1 << 62))]
    for i in range(20):
        chain.append(chain[-1] ^ (1 << (3 * i % 64)) ^ (1 << ((3 * i + 1) % 64)))
    lone = int(rng.integers(1 << 62))
    prints = {i: p for i, p in enumerate([*ball, *chain, lone, lone ^ 0b111])}
    d = spark.createDataFrame([(p - (1 << 64) if p >> 63 else p,) for p in prints.values()], "fp long").distinct()
    edges = [(r["a"] % (1 << 64), r["b"] % (1 << 64)) for r in simhash.links(d).collect()]
    assert all(a in prints.values() and b in prints.values() for a, b in edges)
    parent = {p: p for p in prints.values()}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        parent[root(a)] = root(b)
    want = groups_of(prints)
    for i, j in combinations(prints, 2):
        assert (root(prints[i]) == root(prints[j])) == (want[i] == want[j])


def test_golay_keys_cover_two_bits():
    tables = simhash.golay_tables()
    assert sorted(set(tables[2].tolist())) == [1, 6]
    rng = np.random.default_rng(1)
    base = rng.integers(0, 1 << 63, 300).astype(np.uint64)
    keys = lambda x: [set(k) for k in _by_row(*simhash.keys_of(x, tables), len(x))]
    own = keys(base)
    for _ in range(40):
        a, b = rng.integers(0, 64, 2)
        other = keys(base ^ np.uint64(1 << int(a)) ^ np.uint64((1 << int(b)) if a != b else 0))
        assert all(x & y for x, y in zip(own, other))


def _by_row(at, keys, n):
    out = [[] for _ in range(n)]
    for i, k in zip(at.tolist(), keys.tolist()):
        out[i].append(k)
    return out


def test_pipeline_against_brute_force(spark, small, docs, rows):
    stage = dict(corpus_pipeline.STAGES)
    ids = lambda d: Counter(r["doc_id"] for r in d.collect())
    good = stage["quality rules"](spark, docs, small).cache()
    ledger = {r["doc_id"]: r["failed"] for r in quality.ledger(docs).collect()}
    assert ids(good) == Counter(i for i in ledger if not ledger[i])
    texts = dict(rows)
    best = {}
    for i in ids(good):
        key = re.sub(r"[\x20\x09-\x0D]", "", texts[i])
        best[key] = min(best.get(key, (0, 1 << 60)), (-len(texts[i]), i))
    unique = stage["exact dedup"](spark, good, small).cache()
    assert ids(unique) == Counter(i for _, i in best.values())
    one = stage["simhash near-dedup"](spark, unique, small).cache()
    assert ids(one) == kept_ids({i: texts[i] for i in ids(unique)})  # 0.8 of 5-word shingles: the stage's rule, not the query's
    mix = stage["mixing"](spark, one, small).cache()
    taken = {r["doc_id"]: r["taken"] / r["size"] for r in mixing.mixture(one).collect() if r["size"]}
    assert ids(mix) == Counter({i: int(t + 0.5) for i, t in taken.items() if int(t + 0.5)})
    packed = stage["best-fit packing"](spark, mix, small).collect()
    assert Counter(r["doc_id"] for r in packed if r["piece"] == 0) == ids(mix)
    assert sorted(map(tuple, corpus_pipeline.run(spark, small).select("doc_id", "piece", "length").collect())) == sorted((r["doc_id"], r["piece"], r["length"]) for r in packed)
