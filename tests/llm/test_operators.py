"""Training-data operators against brute force, exact round trips and edge cases."""

from __future__ import annotations

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from normgraph.llm import chat, cotraining, decontaminate, encoding, licences, minhash, rules, suffix, tokenfile, toxicity
from normgraph.llm.bpe import block_encoder
from normgraph.llm.common import table

WORD = re.compile(r"[^\x20\x09-\x0D]+")
VOCAB = "the of and in to was is for with on at by from that this are be as it or an not which but all one had her there been if more when who will no out so up into than them can only other new some".split()


def words(rng, n):
    return " ".join(rng.choice(VOCAB) + str(rng.randint(0, 400)) for _ in range(n))


def frame(spark, rows, extra=False):
    d = spark.createDataFrame(rows, "doc_id long, text string")
    return d.withColumn("score", F.lit("clash")).withColumn("key", F.lit(1)) if extra else d


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and blank texts, repeated rows, ties, a very long text."""
    rng = random.Random(3)
    long = words(rng, 20000)
    return frame(spark, [(1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, "one"), (5, "one"), (None, "two words"), (6, long), (7, long), (8, "licensed under the mit license"), (9, "€ é <|endoftext|> it's 'll 中文  \n x")], True)


# ---- 1


def brute_base(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (text or ""))
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    out = []
    for label, phrase in (("mit", "under the mit license"), ("apache-2", "apache license version 2"), ("cc-by-nc", "cc by nc")):
        p = phrase.split()
        out += [(i, label) for i in range(len(w) - len(p) + 1) if w[i : i + len(p)] == p]
    at = sorted(i for i, _ in out)
    return len(w), len(out), at[0] if at else None, at[-1] if at else None, ",".join(sorted({x for _, x in out}))


def test_licences_against_brute_force(spark, sf):
    rng = random.Random(1)
    pool = ["Under the MIT License", "apache License, Version 2", "CC BY-NC", "cc by nc cc by nc", "underthe mit license", "under the mit licenses", "Apache Licence version 2.0", "é", "x", "-", "\n"]
    rows = [(i, " ".join(rng.choice(pool) for _ in range(rng.randint(0, 9)))) for i in range(300)] + [(r["doc_id"] + 1000, r["text"]) for r in table(spark, sf, "documents", "doc_id", "text").collect()]
    got = {r["doc_id"]: r for r in licences.search_notices(frame(spark, rows)).collect()}
    for i, text in rows:
        r = got[i]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == brute_base(text), text
        assert set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))
        assert 0 <= r["score"] <= 1


def test_licences_fuzzy_spans(spark):
    r = licences.search_notices(frame(spark, [(1, "This is licensed undr the MIT licence today"), (2, "mit of the license")])).orderBy("doc_id").collect()
    assert (r[0]["n_base"], r[0]["labels"]) == (0, "mit")
    assert [(s["label"], s["edits"]) for s in r[0]["spans"]] == [("mit", 2)]
    assert (r[1]["labels"], r[1]["score"]) == ("", 0.0)


def test_licences_chains_and_longer_words(spark):
    texts = ["under the mlt license under the mit license", "under the mit licensed", "gnu general public licenses", "under the mlt license under the mit licensed", "under the mit licensedddd", "acc by nc", "under the mlt license " * 3 + "under the mit license"]
    got = [[(s["label"], s["first_word"], s["end_word"], s["edits"]) for s in r["spans"]] for r in licences.search_notices(frame(spark, list(enumerate(texts)))).orderBy("doc_id").collect()]
    assert got[0] == [("mit", 0, 4, 1), ("mit", 4, 8, 0)]
    assert got[1] == [("mit", 0, 4, 1)] and got[2] == [("gpl", 0, 4, 1)]
    assert got[3] == [("mit", 0, 4, 1), ("mit", 4, 8, 1)]
    assert got[4] == got[5] == []
    assert got[6] == [("mit", 0, 4, 1), ("mit", 4, 8, 1), ("mit", 8, 12, 1), ("mit", 12, 16, 0)]


# ---- 2, 4


def test_encoding_equals_the_library(spark, sf, odd):
    enc = block_encoder(encoding.vocabulary_path())
    for d in (table(spark, sf, "documents", "doc_id", "text"), odd):
        for r in d.select("text").withColumn("doc_id", F.monotonically_increasing_id()).join(encoding.round_trip(d.select("text").withColumn("doc_id", F.monotonically_increasing_id())), "doc_id").collect():
            ids = enc.tokenizer.encode(r["text"] or "", add_special_tokens=False).ids
            assert r["n_tokens"] == len(ids)
            assert r["ids_sha256"] == hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest()
            assert r["decoded_sha256"] == hashlib.sha256(enc.tokenizer.decode(ids, skip_special_tokens=False).encode()).hexdigest()


def test_encode_then_decode(spark, odd):
    d = odd.where("doc_id in (4, 8, 9)")
    back = {r["doc_id"]: r["text"] for r in encoding.decode(encoding.encode(d)).collect()}
    assert back == {r["doc_id"]: r["text"] for r in d.select("doc_id", "text").collect()}


def test_words_split_as_the_library():
    enc = block_encoder(encoding.vocabulary_path())
    rng = random.Random(2)
    alphabet = [*"aZ é1 \n\t'.,!", "  ", "'s", " 'll", "'LL", "<|endoftext|>", "中文", "😀", "\x85", "don't"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 30))) for _ in range(3000)]
    ids, counts = enc.encode(texts)
    edges = np.concatenate([[0], np.cumsum(counts)])
    for i, t in enumerate(texts):
        assert ids[edges[i] : edges[i + 1]].tolist() == enc.tokenizer.encode(t, add_special_tokens=False).ids, repr(t)


def test_token_file(spark, sf, odd):
    enc = block_encoder(encoding.vocabulary_path())
    for d in (table(spark, sf, "documents", "doc_id", "text"), odd):
        rows = sorted(((r["doc_id"], r["text"] or "") for r in d.select("doc_id", "text").collect()), key=lambda x: (x[0] is not None, x[0] or 0, x[1]))
        got = tokenfile.read_documents(tokenfile.write_shards(d, cfg=tokenfile.RePairConfig(shard_ids=5000))).collect()
        got = {(r["doc_id"], r["start"]): r for r in got}
        at = 0
        for doc, text in rows:
            ids = [*enc.tokenizer.encode(text, add_special_tokens=False).ids, 2]
            r = got[(doc, at)]
            assert (r["n_tokens"], r["ids_crc32"]) == (len(ids), zlib.crc32(np.array(ids, dtype="<u4").tobytes()))
            at += len(ids)
        assert len(got) == len(rows)


@pytest.mark.parametrize("ids", [[], [5], [7] * 1000, [1, 2] * 3000, list(range(3000)), [2**31, 2**31, 1] * 50])
def test_grammar_round_trip_and_random_access(ids):
    ids = np.array(ids, dtype=np.uint32)
    raw = tokenfile.compress(ids, tokenfile.RePairConfig(min_count=2))
    s = tokenfile.Shard(raw)
    assert s.decode().tolist() == ids.tolist()
    for a, n in ((0, 1), (3, 10), (900, 50), (len(ids) - 1, 5)):
        assert s.decode(max(a, 0), n).tolist() == ids[max(a, 0) : max(a, 0) + n].tolist()


# ---- 3


def brute_repeats(rows, n=50):
    where = {}
    for d, t in rows:
        w = WORD.findall(t or "")
        for i in range(len(w) - n + 1):
            where.setdefault(tuple(w[i : i + n]), []).append((d, i))
    return {p for places in where.values() if len({d for d, _ in places}) > 1 for p in places}


def test_suffix_repeats_against_brute_force(spark):
    rng = random.Random(4)
    shared = [words(rng, n) for n in (49, 50, 51, 80, 300)]
    rows = [(i, " ".join([words(rng, rng.randint(0, 60)), rng.choice(shared), words(rng, rng.randint(0, 60)), *([rng.choice(shared)] if i % 3 == 0 else [])])) for i in range(60)] + [(100, shared[4]), (101, shared[4]), (102, None), (103, "")]
    want = brute_repeats(rows)
    covered = {(r["doc_id"], s) for r in suffix.repeated_spans(frame(spark, rows, True)).collect() for s in range(r["first_word"], r["end_word"] - 49)}
    assert want <= covered
    assert {d for d, _ in covered} == {d for d, _ in want}
    left = suffix.remove_repeats(frame(spark, rows)).collect()
    assert not brute_repeats([(r["doc_id"], r["text"]) for r in left])
    assert {r["doc_id"] for r in left} >= {102, 103}
    assert 100 not in {r["doc_id"] for r in left} or 101 not in {r["doc_id"] for r in left}


def all_places(rows, n=50):
    where = {}
    for d, t in rows:
        w = WORD.findall(t or "")
        for i in range(len(w) - n + 1):
            where.setdefault(tuple(w[i : i + n]), []).append((d, i))
    return {p for places in where.values() if len(places) > 1 for p in places}


def test_suffix_repeats_inside_one_document(spark):
    """Self-repeats, apart and overlapping, are found and go; the first copy stays whole."""
    rng = random.Random(14)
    a, b, c = words(rng, 60), words(rng, 40), words(rng, 55)
    rows = [(1, f"{a} {b} {a}"), (2, "x y z " * 60), (3, f"{words(rng, 20)} {c} {c} {c}"), (4, words(rng, 150)), (5, None)] + [(7, f"p {a[::-1]} q")] * 2
    cfg = suffix.RepeatConfig(across=False)
    want = all_places(dict(rows).items())
    spans = suffix.repeated_spans(frame(spark, rows), cfg).collect()
    assert {(r["doc_id"], s) for r in spans for s in range(r["first_word"], r["end_word"] - 49)} >= want
    assert {r["doc_id"] for r in spans} == {d for d, _ in want} == {1, 2, 3}
    left = {r["doc_id"]: r["text"] for r in suffix.remove_repeats(frame(spark, rows), cfg).collect()}
    assert not all_places(left.items())
    assert left[1].split() == f"{a} {b}".split() and left[2].split() == ("x y z " * 17).split()[:50]
    assert left[3].split() == rows[2][1].split()[:75] and left[4] == rows[3][1]


# ---- 5


def test_rotation(spark):
    d = spark.createDataFrame([(1, 0, "ann", "hi"), (1, 1, "bob", "yo"), (1, 1, "bob", "yo"), (1, 2, "ann", None), (None, 0, "x", "y")], "conv_id long, turn long, role string, text string")
    got = {r["participant"]: r for r in chat.rotate(d.withColumn("block", F.lit(9))).collect()}
    assert set(got) == {"ann", "bob"}
    r = got["ann"]
    assert r["rendered"] == "<|start|>assistant\nhi<|end|>\n<|start|>user name=bob\nyo<|end|>\n<|start|>assistant\n<|end|>\n"
    assert [r["rendered"][m["start"] : m["end"]] for m in r["mask"]] == ["hi<|end|>\n", "<|end|>\n"]
    assert [got["bob"]["rendered"][m["start"] : m["end"]] for m in got["bob"]["mask"]] == ["yo<|end|>\n"]


# ---- 6


def brute_components(rows, k, percent):
    sets = {}
    for d, t in rows:
        w = WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (t or "")))
        sets[d] = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} or ({tuple(w)} if w else set())
    ids = sorted(sets)
    root = {d: d for d in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {d: (len(sets[d]), find(d)) for d in ids}


def test_near_duplicates_against_brute_force(spark):
    rng = random.Random(5)
    rows, base = [], [words(rng, n) for n in (8, 30, 120, 400)]
    for i in range(240):
        w = rng.choice(base).split()
        for _ in range(rng.randint(0, max(1, len(w) // 9))):
            w[rng.randrange(len(w))] = "new" + str(rng.randint(0, 9))
        rows.append((i, " ".join(w)))
    rows += [(300, None), (301, ""), (302, "one"), (303, "ONE"), (304, "\n")]
    for k in (2, 5):
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in minhash.near_duplicates(frame(spark, rows, True), minhash.NearDupConfig(words=k)).collect()}
        assert got == brute_components(rows, k, 80)


# ---- 7


def test_co_training(spark, sf):
    docs, labels = table(spark, "/root/testdata/sf0.01", "documents"), table(spark, "/root/testdata/sf0.01", "labels")
    x, m, y = cotraining.training_views(docs, labels, cotraining.CoTrainingConfig())
    pool = y < 0
    model = cotraining.co_train(x[~pool], m[~pool], y[~pool], x[pool], m[pool])
    assert model.history[-1]["meta_rows"] > model.history[0]["meta_rows"]
    got = cotraining.score(docs, model).join(labels, "doc_id")
    right = got.agg(F.avg((F.col("kept") == (F.col("quality") == 1)).cast("double"))).first()[0]
    base = labels.agg(F.avg("quality")).first()[0]
    assert right > base


def test_co_training_offers_every_unlabelled_document(spark):
    docs, labels = table(spark, "/root/testdata/sf0.01", "documents"), table(spark, "/root/testdata/sf0.01", "labels")
    few = cotraining.CoTrainingConfig(n_pool=10)
    assert sum(cotraining.fit(docs, labels, few).history[-1][k] - cotraining.fit(docs, labels, few).history[0][k] for k in ("text_rows", "meta_rows")) > 10
    x, m, y = cotraining.training_views(docs, labels, cotraining.CoTrainingConfig(n_pool=10**6))
    model = cotraining.Logistic(x[y >= 0], y[y >= 0])
    for label in (0.0, 1.0):
        want = cotraining.HeldPool(x[y < 0], m[y < 0]).surest("text", model, label, 30, 0.6)
        spread = cotraining.spread_pool(docs.repartition(7), labels, few)
        got = spread.surest("text", model, label, 30, 0.6)
        assert np.allclose(np.sort(model.odds(want[0])), np.sort(model.odds(got[0]))) and len(got[0]) == 30
        assert not spread.taken & {r["doc_id"] for r in labels.collect()}
        assert got[1].sum(1).tolist() == [3.0] * 30


def test_co_training_without_labels(spark, odd):
    d = odd.select("doc_id", "text", F.lit(None).cast("string").alias("lang"), F.lit(None).cast("string").alias("source"), F.lit(None).cast("long").alias("n_chars"))
    empty = spark.createDataFrame([], "doc_id long, quality int")
    assert cotraining.classify(d, empty).where("kept").count() == odd.count()


# ---- 8


def test_line_rules_counts(spark, sf, odd):
    rows = table(spark, sf, "documents", "doc_id", "text").unionByName(odd.select(F.col("doc_id") + 5000, "text").toDF("doc_id", "text"))
    for r in rows.join(rules.score_documents(rows.dropDuplicates()).withColumnRenamed("doc_id", "d"), F.col("doc_id") == F.col("d")).collect():
        t = r["text"] or ""
        w = WORD.findall(t)
        where = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
        under = {j for i in range(len(w) - 7) if where[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        want = (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(under))
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
        assert r["base_failed"] == (len(w) < 20 or 100 * len(under) > 30 * len(w))


def test_line_rules_remove_lines(spark):
    body = "\n".join(words(random.Random(i), 30) for i in range(4))
    d = frame(spark, [(1, body + "\nHome | News | About | Contact\nWe use cookies. Click here"), (2, "\n".join(["a | b | c | d"] * 40))])
    got = {r["doc_id"]: r for r in rules.score_documents(d).collect()}
    assert got[1]["clean_text"] == body and got[1]["kept"]
    assert not got[2]["kept"]


# ---- 9


def test_toxicity_held_out(spark):
    docs, labels = table(spark, "/root/testdata/sf0.1", "documents"), table(spark, "/root/testdata/sf0.1", "labels")
    got = toxicity.classify(docs, labels).join(labels, "doc_id").where("crc32(cast(doc_id as string)) % 5 = 0")
    r = got.agg(F.avg((F.col("predicted") == F.col("toxic")).cast("double")).alias("acc"), F.avg((F.col("toxic") == 0).cast("double")).alias("base")).first()
    assert r["acc"] > 0.95 > r["base"]


def test_toxicity_calibrated_to_all_labels_when_both_caps_bind(spark):
    """Caps of 1 : 1 against a true share of about 1 : 8; the mean score of held-out rows follows the true share."""
    docs, labels = table(spark, "/root/testdata/sf0.1", "documents"), table(spark, "/root/testdata/sf0.1", "labels")
    held = labels.where("crc32(cast(doc_id as string)) % 5 = 0")
    cfg = toxicity.ToxicityConfig(n_toxic=300, n_ordinary=300)
    r = toxicity.classify(docs, labels, cfg).join(held, "doc_id").agg(F.avg("score").alias("mean"), F.avg("toxic").alias("share"), F.avg((F.col("predicted") == F.col("toxic")).cast("double")).alias("acc")).first()
    assert abs(r["mean"] - r["share"]) < 0.03
    rest = labels.where("crc32(cast(doc_id as string)) % 5 <> 0").groupBy("toxic").count().collect()
    n = {x["toxic"]: x["count"] for x in rest}
    assert toxicity.sampling_shift(labels, cfg) == pytest.approx(np.log(n[1] / n[0]))
    assert toxicity.sampling_shift(labels, toxicity.ToxicityConfig(n_toxic=10**6, n_ordinary=10**6)) == 0.0


def test_toxicity_against_single_windows(spark, sf):
    """Scores of whole texts from windows cut and compressed one by one."""
    import zstandard

    docs, labels = table(spark, "/root/testdata/sf0.01", "documents", "doc_id", "text"), table(spark, "/root/testdata/sf0.01", "labels", "doc_id", "toxic")
    model = toxicity.fit(docs, labels)
    cfg = model.config
    params = zstandard.ZstdCompressionParameters.from_level(cfg.level, min_match=3, format=zstandard.FORMAT_ZSTD1_MAGICLESS, write_content_size=False, write_checksum=False, write_dict_id=False)

    def size(content, window):
        known = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        return len(zstandard.ZstdCompressor(dict_data=known, compression_params=params).compress(window))

    some = table(spark, sf, "documents", "doc_id", "text").where("length(text) < 1500").limit(12)
    for r in toxicity.score(some, model).join(some, "doc_id").collect():
        w = re.findall(rb"[a-z\x80-\xff]+", (r["text"] or "").encode().lower())
        spans = [w[i : i + 5] for i in range(0, len(w), 4) if i == 0 or i + 1 < len(w)]
        gains = np.array([size(model.ordinary, x) - size(model.toxic + model.ordinary, x) for x in (model.ordinary[-48:] + b" " + b" ".join(s) + b" " for s in spans)])
        x = (np.array(toxicity._summary(gains)) - model.mean) / model.scale
        p = 1 / (1 + np.exp(-np.clip(model.weights[0] + x @ model.weights[1:], -30, 30)))
        assert r["score"] == pytest.approx(p) and r["predicted"] == int(p >= 0.5)


def test_toxicity_dictionaries_are_of_their_class():
    rng = random.Random(8)
    texts = [(words(rng, 60).encode(), 0) for _ in range(200)] + [((words(rng, 30) + " vile wretch " + words(rng, 30)).encode(), 1) for _ in range(60)]
    model = toxicity.train(texts, toxicity.ToxicityConfig())
    assert b"vile" in model.toxic and b"vile" not in model.ordinary and b"wretch" not in model.ordinary


def test_toxicity_without_two_classes(spark, odd):
    empty = spark.createDataFrame([], "doc_id long, toxic int")
    assert toxicity.classify(odd, empty).where("predicted = 0").count() == odd.count()


# ---- 10


def brute_leaks(rows, items, k=5, least=0.8):
    out = set()
    gram = lambda w, n: Counter(tuple(w[i : i + n]) for i in range(len(w) - n + 1))
    item_words = {i: WORD.findall(t.lower()) for i, t in items}
    use = Counter(g for w in item_words.values() for g in set(gram(w, min(k, len(w)))))
    for d, t in rows:
        w = WORD.findall((t or "").lower())
        for i, iw in item_words.items():
            n = min(k, len(iw))
            own = gram(iw, n)
            for s in range(len(w) - len(iw) + 1):
                win = gram(w[s : s + len(iw)], n)
                if own.keys().isdisjoint(win):
                    continue
                wt = lambda g: np.log1p(len(items) / use[g]) if g in use else np.log1p(len(items))
                both = sum(wt(g) * min(own[g], win[g]) for g in own.keys() | win.keys())
                union = sum(wt(g) * max(own[g], win[g]) for g in own.keys() | win.keys())
                if both >= least * union:
                    out.add((d, i))
    return out


def test_leaks_against_brute_force(spark):
    rng = random.Random(6)
    items = [(i, words(rng, n)) for i, n in enumerate((3, 12, 25, 40, 60, 60))] + [(6, "")]
    rows = []
    for i in range(120):
        w = rng.choice(items)[1].split()
        for _ in range(rng.choice((0, 0, 1, 1, 2))):
            if w:
                w[rng.randrange(len(w))] = "edit"
        rows.append((i, " ".join([words(rng, rng.randint(0, 30)), *w, words(rng, rng.randint(0, 30))])))
    rows += [(200, None), (201, ""), (202, words(rng, 500))]
    bench = spark.createDataFrame([*items, (None, "x y z")], "item_id long, text string")
    want = brute_leaks(rows, items[:6])
    for size in (decontaminate.MAX_ITEM_BYTES, 600):  # one block of items, and several
        got = {(r["doc_id"], r["item_id"]) for r in decontaminate.find_leaks(frame(spark, rows, True), bench, max_item_bytes=size).collect()}
        if size == decontaminate.MAX_ITEM_BYTES:
            assert got == want
        assert got >= {x for x in want if x[1] in (3, 4, 5)}
    left = {r["doc_id"] for r in decontaminate.remove_leaks(frame(spark, rows), bench).collect()}
    assert left == {d for d, _ in rows} - {d for d, _ in want}


def test_leaks_of_documents_shorter_than_the_item(spark):
    rng = random.Random(16)
    items = [(i, words(rng, n)) for i, n in enumerate((38, 38, 40, 6))]
    w = [t.split() for _, t in items]
    rows = [(1, " ".join(w[0][:-1])), (2, " ".join(w[0][3:])), (3, " ".join(w[1][:20])), (4, " ".join(w[3][:5])), (5, " ".join(w[2][:20] + w[2][21:])), (6, " ".join(w[0]))]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): (r["first_word"], r["end_word"], round(r["similarity"], 6)) for r in decontaminate.find_leaks(frame(spark, rows), bench).collect()}
    assert got == {(1, 0): (0, 37, round(33 / 34, 6)), (2, 0): (0, 35, round(31 / 34, 6)), (6, 0): (0, 38, 1.0)}


def test_leaks_do_not_depend_on_blocks_of_items(spark):
    """Items share passages, so that weights decide; several blocks give what one gives, similarity included."""
    rng = random.Random(17)
    common = words(rng, 12)
    items = [(i, f"{words(rng, 20)} {common} {words(rng, 4)}") for i in range(40)]
    rows = []
    for i in range(200):
        w = rng.choice(items)[1].split()
        for _ in range(rng.choice((0, 1, 1, 2))):
            w[rng.randrange(len(w))] = "edit"
        rows.append((i, " ".join(w[rng.randint(0, 3) :])))
    bench = spark.createDataFrame(items, "item_id long, text string")
    one, many = (sorted((*r[:4], round(r[4], 9)) for r in decontaminate.find_leaks(frame(spark, rows), bench, max_item_bytes=n).collect()) for n in (decontaminate.MAX_ITEM_BYTES, 1500))
    assert one == many and one


# ---- all


@pytest.mark.parametrize(
    "run",
    [
        licences.search_notices, encoding.encode, encoding.round_trip, suffix.repeated_spans, suffix.remove_repeats, minhash.near_duplicates, minhash.keep_one_of_each, rules.score_documents,
        lambda d: tokenfile.read_documents(tokenfile.write_shards(d)),
    ],
)
def test_odd_and_empty_tables(run, odd):
    assert run(odd.limit(0)).count() == 0
    run(odd).collect()


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = table(spark, sf, "documents")
    out = corpus_pipeline.run(spark, sf)
    assert 0 < out.count() < docs.count()
    kept = docs.join(out.select("doc_id"), "doc_id", "left_semi")
    comps = brute_components([(r["doc_id"], r["text"]) for r in kept.collect()], 5, 80)
    assert all(c == d for d, (n, c) in comps.items() if n)


def test_near_duplicates_of_many_altered_copies(spark, monkeypatch):
    """2,000 altered copies of one text, most of them no links of each other, in blocks far smaller than the group."""
    rng = random.Random(21)
    base = words(rng, 60).split()
    rows = []
    for i in range(2000):
        w = list(base)
        for at in rng.sample(range(60), rng.randint(0, 9)):
            w[at] = rng.choice(VOCAB) + str(rng.randint(0, 5))
        rows.append((i, " ".join(w)))
    monkeypatch.setattr(minhash, "BLOCK", 64)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in minhash.near_duplicates(frame(spark, rows)).collect()}
    assert got == brute_components(rows, 2, 80)


def test_odd_sketches_never_overstate_the_difference():
    rng = np.random.default_rng(1)
    for n in (1, 30, 500, 5000):
        a = np.unique(rng.integers(0, 2**63, n, dtype=np.uint64))
        b = np.unique(np.concatenate([a[: n // 2], rng.integers(0, 2**63, n, dtype=np.uint64)]))
        x, y = (np.frombuffer(minhash.odd_sketch(v), dtype=np.uint64) for v in (a, b))
        assert int(np.bitwise_count(x ^ y).sum()) <= len(np.setxor1d(a, b))


@pytest.mark.parametrize("head", [0, 3000])
def test_encoding_of_words_that_are_not_broadcast(spark, sf, odd, head):
    """With no or a tiny table of common words all others come through the join; results are the same."""
    d = table(spark, sf, "documents", "doc_id", "text").limit(60).unionByName(odd.select("doc_id", "text"))
    want = sorted(encoding.round_trip(d).collect(), key=str)
    assert sorted(encoding.round_trip(d, head_bytes=head).collect(), key=str) == want
    ids = {(r["doc_id"], str(r["ids"])) for r in encoding.encode(d, head_bytes=head).collect()}
    assert ids == {(r["doc_id"], str(r["ids"])) for r in encoding.encode(d).collect()}


def test_decode_through_the_piece_table(spark):
    enc = block_encoder(encoding.vocabulary_path())
    rows = [(1, None), (2, []), (3, [10**6, 5, None]), (4, enc.tokenizer.encode("né <|endoftext|> 中文", add_special_tokens=False).ids), (4, [enc.tokenizer.encode("中", add_special_tokens=False).ids[0]])]
    d = spark.createDataFrame(rows, "doc_id long, ids array<int>")
    got = sorted((r["doc_id"], r["text"]) for r in encoding.decode(d).collect())
    assert got == sorted((i, enc.tokenizer.decode([x for x in ids or [] if x is not None and x < 10**5], skip_special_tokens=False)) for i, ids in rows)
    assert encoding.decode(d.limit(0)).count() == 0


def test_leaks_with_swapped_halves_and_altered_ends(spark):
    """Windows far from where the shared shingles stand in the item, and pairs close to the similarity; every block size."""
    rng = random.Random(18)
    items = [(i, words(rng, n)) for i, n in enumerate([60] * 6 + [40] * 20)]
    rows = []
    for i, text in items:
        w = text.split()
        half = len(w) // 2
        rows.append((i, " ".join([words(rng, 7), *w[half:], *w[:half], words(rng, 9)])))
        for cut in (2, 3, 4, 5):
            rows.append((100 * cut + i, " ".join([words(rng, 5), *w[:-cut], *words(rng, cut).split(), words(rng, 6)])))
            rows.append((1000 * cut + i, " ".join([words(rng, 5), *words(rng, cut).split(), *w[cut:]])))
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = brute_leaks(rows, items)
    assert {(i, i) for i in range(6)} <= want
    for size in (decontaminate.MAX_ITEM_BYTES, 3000):
        assert {(r["doc_id"], r["item_id"]) for r in decontaminate.find_leaks(frame(spark, rows, True), bench, max_item_bytes=size).collect()} == want


def test_multi_index_finds_every_print_in_the_radius():
    rng = np.random.default_rng(3)
    items = [(i, " ".join(f"w{rng.integers(0, 10**6)}" for _ in range(20)).encode()) for i in range(300)]
    index = decontaminate.ItemIndex(items, decontaminate.DecontaminationConfig())
    for _ in range(300):
        mark = np.unpackbits(index.prints[rng.integers(0, 300)])
        flip = rng.choice(128, rng.integers(0, 60), replace=False)
        mark[flip] ^= 1
        mark = np.packbits(mark)
        far = np.bitwise_count(index.prints ^ mark).sum(1)
        assert index.near(mark) == np.flatnonzero(far <= decontaminate.RADIUS).tolist()


def test_leaks_of_any_id_type_and_clashing_columns(spark):
    text = words(random.Random(2), 40)
    docs = spark.createDataFrame([("a", text, 1), ("b", "x", 2), (None, text, 3)], "doc_id string, text string, item_id int")
    bench = spark.createDataFrame([(7.5, text), (1.0, None)], "item_id double, text string")
    assert sorted((r["doc_id"] or "", r["item_id"]) for r in decontaminate.find_leaks(docs, bench).collect()) == [("", 7.5), ("a", 7.5)]
    assert sorted(r["item_id"] for r in decontaminate.remove_leaks(docs, bench).collect()) == [2, 3]
    assert decontaminate.find_leaks(docs, bench.limit(0)).count() == 0 == decontaminate.find_leaks(docs.limit(0), bench).count()


def test_repeats_with_unlike_neighbours(spark):
    """Copies whose left and right contexts agree with different other copies, many copies of one passage, clashing columns."""
    rng = random.Random(24)
    core = words(rng, 24)
    lefts, rights = [words(rng, 30) for _ in range(3)], [words(rng, 30) for _ in range(3)]
    rows = [(i, " ".join([words(rng, rng.randint(0, 9)), rng.choice(lefts), core, rng.choice(rights), words(rng, rng.randint(0, 9))])) for i in range(80)]
    rows += [(200 + i, " ".join([rng.choice(lefts).split(" ", 20)[-1], core, rng.choice(rights)[:60]])) for i in range(20)]
    rows += [(300 + i, f"{words(rng, i % 5)} {lefts[0]} {lefts[1]}") for i in range(150)]
    for across in (True, False):
        cfg = suffix.RepeatConfig(across=across)
        want = brute_repeats(rows) if across else all_places(rows)
        d = frame(spark, rows, True).repartition(7)
        covered = {(r["doc_id"], s) for r in suffix.repeated_spans(d, cfg).collect() for s in range(r["first_word"], r["end_word"] - 49)}
        assert covered >= want and {x for x, _ in covered} == {x for x, _ in want}
    left = suffix.remove_repeats(frame(spark, rows).withColumn("_cut", F.lit(1)).withColumn("_cut_id", F.lit(2)).withColumn("ranges", F.lit(3)), cfg)
    assert left.columns == ["doc_id", "text", "_cut", "_cut_id", "ranges"]
    assert not all_places([(r["doc_id"], r["text"]) for r in left.collect()])


def test_windows_are_sent_once_for_each_document(spark):
    """A text of a short period sends its three distinct windows, with all their places, and not 131 rows."""
    for across, rows in ((False, [(1, "x y z " * 60)]), (True, [(1, "x y z " * 60), (2, "a " + "x y z " * 60)])):
        cfg = suffix.RepeatConfig(across=across)
        d = frame(spark, rows)
        got = [r for r in suffix.windows(d, suffix.extensible(d, cfg), cfg).collect() if r["doc_id"] == 1]
        assert len(got) == len({(r["h"], r["h2"]) for r in got}) == 3
        assert sorted(s for r in got for s in [r["start"], *(r["more"] or [])]) == list(range(131))


def test_neighbours_of_other_documents(spark, monkeypatch):
    """With ``across`` a suffix shares as much as with the nearest of another document, never less, whatever the batches."""
    rng = random.Random(33)
    rows = sorted((bytes(rng.choice((0, 1, 16, 17)) for _ in range(5)), b"", rng.randint(0, 3), i) for i in range(400))
    rows += sorted((b"\x77" + bytes(rng.choice((0, 1)) for _ in range(4)), b"", 9, 1000 + i) for i in range(300))
    d = spark.createDataFrame(rows, "suffix binary, before binary, doc_id long, pos int").coalesce(1)

    def shared(a, b):
        a, b = ([x for c in v for x in (c >> 4, c & 15)] for v in (a, b))
        return next((i for i, (x, y) in enumerate(zip(a, b, strict=True)) if x != y), len(a))

    want = {r[3]: max(shared(r[0], o[0]) for o in rows if o[2] != r[2]) for r in rows}
    for size in (10000, 37):
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
        try:
            found = suffix._with_neighbours(d.sortWithinPartitions("suffix", "doc_id", "pos"), "suffix", 0, "pos int, reach int", ["pos"], "reach", 0, True).collect()
        finally:
            spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
        got = {r["pos"]: r["reach"] for r in found}
        assert all(got[i] >= n for i, n in want.items())
        if size > len(rows):
            last = max(rows)[3]
            assert sum(got[i] > want[i] for i in want) <= 2 + sum(1 for r in rows if r[2] == max(rows)[2] and shared(r[0], max(rows)[0])), last


def test_shuffle_files_go_when_a_table_is_written(spark):
    from normgraph.llm import common

    files = lambda: {f for f in spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString("|").split("|") if "shuffle_" in f}
    before = files()
    out = common.materialise(spark.range(1000).repartition(3, "id").groupBy((F.col("id") % 7).alias("k")).count(), "shuffled")
    assert not files() - before
    assert out.count() == 7


def test_head_words_are_held_in_narrow_numbers():
    import pyarrow as pa

    lexicon = encoding.Lexicon(np.array([9, 3], dtype=np.uint64), pa.array([[7, 40000], [1]], pa.list_(pa.int32())), pa.array([None, b"ab"], pa.binary()))
    assert lexicon.ids.tolist() == [1, 7, 40000] and lexicon.ids.itemsize == 2
    assert lexicon.id_offs.tolist() == [0, 1, 3] and lexicon.byte_offs.tolist() == [0, 2, 2] and lexicon.byte_offs.itemsize == 1
