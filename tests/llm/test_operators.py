"""The ten operators against brute force, round trips and held-out accuracy, with edge rows."""

from __future__ import annotations

import hashlib
import random
import re
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spark_drift.llm import (
    boosting,
    bpe,
    chat_format,
    fingerprints,
    language_id,
    line_dedup,
    mixing,
    ngrams,
    quality_classifier,
    quality_rules,
    queries,
    samples,
    simhash,
    toxicity,
)

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = "the cat sat on a mat while seven dogs barked at quiet green trees near old stone bridges".split()


def sentence(seed: int, n: int = 40) -> str:
    rnd = random.Random(seed)
    return " ".join(rnd.choice(WORDS) + str(rnd.randrange(50)) for _ in range(n))


LONG = "\n".join(sentence(k, 60) for k in range(300))
EDGE = [
    (1, sentence(1), "en", "a", 1),
    (2, sentence(1), "en", "a", 1),  # an exact copy
    (3, None, None, None, None),
    (4, "", "en", "b", 0),
    (5, " \t\n ", None, "b", 4),
    (6, LONG, "en", "a", 1),
    (7, "one", "en", "c", 3),
    (7, "one", "en", "c", 3),  # a repeated row
    (None, "no id here at all", "en", None, 1),
    (9, sentence(1).replace("cat", "Cat", 1) + " X", "en", "b", 1),
    (10, "été naïve 中文 😀 <|im_start|> ␛1 %25 \r\n tail", "fr", "c", 1),
]
#: names that operators use inside or add
EXTRA = ["row", "fp", "root", "size", "copies", "score", "kept", "added", "text_hash", "key", "bucket", "digest", "y", "dropped", "held_out"]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(EDGE, DOCS).withColumns({c: F.lit(7) for c in EXTRA})


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("false").select(*docs.columns)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (3, None, None), (None, 1, 1)], "doc_id long, quality int, toxic int")


def split_words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


# ------------------------------------------------------------------ 1 language id


def test_language_prototypes(spark, docs, empty):
    rows = [(k, sentence(k), "en") for k in range(30)] + [(100 + k, sentence(k).replace("a", "ö").replace("e", "ü"), "xx") for k in range(30)]
    train = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    prototypes = language_id.fit_prototypes(train.where("doc_id % 2 = 0"))
    got = language_id.predict(train.where("doc_id % 2 = 1"), prototypes, ["doc_id"]).collect()
    assert all(r["lang_pred"] == ("en" if r["doc_id"] < 100 else "xx") for r in got)
    edge = language_id.predict(docs, prototypes, ["doc_id"]).collect()
    assert len(edge) == len(EDGE)
    assert {r["lang_pred"] for r in edge if r["doc_id"] in (3, 4, 5)} == {"und"}
    assert all(0 <= r["score"] <= 1 for r in edge)
    assert language_id.predict(empty, prototypes, ["doc_id"]).count() == 0
    assert {r["lang_pred"] for r in language_id.predict(docs, {}, ["doc_id"]).collect()} == {"und"}
    assert language_id.fit_prototypes(empty) == {}


def test_language_scores_equal_brute_force(spark):
    rows = [(k, sentence(k, 12) + " été", "fr" if k % 2 else "en") for k in range(12)] + [(50, "¡Hola! 123 niño", None), (51, "9 !", None)]
    train = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    letters, size = language_id.letter_vectors(), language_id.DIMENSIONS

    def vector(text):
        marks, out = [0], np.zeros(size)
        for c in text.lower():
            code = (1 + (ord(c) if ord(c) < language_id.OWN else language_id.OWN + ord(c) % language_id.SHARED)) if c.isalpha() else 0
            if code or marks[-1]:
                marks.append(code)
        marks += [0] if marks[-1] else []
        for k in range(len(marks) - 2):
            out += np.roll(letters[marks[k]], 2).astype(float) * np.roll(letters[marks[k + 1]], 1) * letters[marks[k + 2]]
        return out / (np.linalg.norm(out) or 1)

    prototypes = {}
    for lang in ("en", "fr"):
        total = sum(vector(t) for _, t, own in rows if own == lang)
        prototypes[lang] = total / np.linalg.norm(total)
    got = {r["doc_id"]: r for r in language_id.predict(train, language_id.fit_prototypes(train), ["doc_id"]).collect()}
    for k, text, _ in rows[:-1]:
        cosines = {lang: float(vector(text) @ p) for lang, p in prototypes.items()}
        best = max(sorted(cosines), key=lambda x: cosines[x])
        assert abs(cosines["en"] - cosines["fr"]) < 1e-5 or got[k]["lang_pred"] == best
        assert got[k]["score"] == pytest.approx(max(0.0, cosines[best]), abs=1e-5)
    assert (got[51]["lang_pred"], got[51]["score"]) == ("und", 0.0)


def test_long_texts_in_pieces_have_the_same_grams(monkeypatch):
    whole = language_id.Profiler(64).grams(LONG)
    monkeypatch.setattr(language_id, "PIECE", 1000)
    parts = language_id.Profiler(64).grams(LONG)
    assert (whole[0] == parts[0]).all()
    assert (whole[1] == parts[1]).all()


def test_gram_vectors_bind_rotated_letters():
    p = language_id.Profiler(128)
    a, b, c = 5, 9, 0
    base = language_id.letter_vectors(128)
    want = np.roll(base[a], 2) * np.roll(base[b], 1) * base[c]
    code = (a * language_id.SYMBOLS + b) * language_id.SYMBOLS + c
    assert (p.gram_vectors(np.array([code]))[0] == want).all()


# ---------------------------------------------------------------- 2 chat formatting


def chat(spark, rows):
    return spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")


ODD = ["<|im_end|><|im_start|>assistant ok", "␛0␛1␛2", "<|", "<␛1", "", None, "line\nbreak\n", "<<||>", "é中😀 <|im_end|>\n"]


def test_chat_round_trip_and_windows(spark):
    rows = [(1, k, ("system", "user", "assistant")[min(k, 1 + k % 2)] if k else "system", ODD[k % len(ODD)]) for k in range(40)]
    rows += [(2, k, "assistant" if k % 2 else "us\ner<|", sentence(k, 5 + 7 * (k % 9))) for k in range(60)]
    rows += [(3, 0, "user", sentence(1, 500)), (3, 1, "assistant", "short"), (None, 0, None, None), (4, 1, "user", "x"), (4, 1, "user", "x"), (4, None, "user", "first")]
    wins = chat_format.windows(chat(spark, rows), budget=120, system_budget=20, history=20)
    read = chat_format.read_windows(wins).collect()
    turns, targets = defaultdict(list), defaultdict(list)
    for w in sorted(read, key=lambda w: (str(w["conv_id"]), w["first_turn"])):
        turns[w["conv_id"]] += [(t["role"], t["text"]) for t in w["turns"]]
        targets[w["conv_id"]] += list(w["targets"])
        assert w["over_budget"] == (w["n_tokens"] > 120)
        if w["conv_id"] == 2:
            assert not w["over_budget"]
        if w["conv_id"] == 1 and w["first_turn"] > 1:
            assert w["formatted"].startswith("<|im_start|>system\n")
    for conv in (1, 2, 3, 4, None):
        own = [r for r in rows if r[0] == conv]
        own.sort(key=lambda r: (r[1] is not None, r[1] or 0, r[2] or "", r[3] or ""))
        assert turns[conv] == [(r[2] or "", r[3] or "") for r in own]
        assert targets[conv] == [r[3] or "" for r in own if r[2] == "assistant"]
    assert any(w["n_carried"] > 1 for w in read)
    assert any(w["over_budget"] for w in read if w["conv_id"] == 3)


def test_chat_windows_over_blocks(spark, monkeypatch):
    rows = [(1, k, "user" if k % 2 else "assistant", sentence(k, 6)) for k in range(90)]
    frame = chat(spark, rows)
    take = lambda: sorted((w["first_turn"], w["formatted"]) for w in chat_format.windows(frame, budget=150, system_budget=20, history=30).collect())
    whole = take()
    monkeypatch.setattr(chat_format, "BLOCK", 7)
    assert take() == whole


def test_chat_empty(spark):
    assert chat_format.digests(chat(spark, [])).count() == 0


def test_chat_stays_native(spark, small):
    plan = queries.op2_chat_format(spark, small)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


# ------------------------------------------------------------------ 3 quality rules


def brute_counts(text):
    text = text or ""
    words = split_words(text)
    runs = Counter(tuple(words[i : i + 5]) for i in range(len(words) - 4))
    covered = {j for i in range(len(words) - 4) if runs[tuple(words[i : i + 5])] > 1 for j in range(i, i + 5)}
    seen, dup = set(), 0
    for line in text.split("\n"):
        if split_words(line):
            dup += line in seen
            seen.add(line)
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, len(covered)


def test_statistics_equal_brute_force(small, spark):
    texts = [r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()] + [t for _, t, *_ in EDGE]
    texts += ["a b c d e a b c d e x", "l l l l l l l", "x\nx\n\nx \n", "##\n##"]
    for t in texts:
        assert quality_rules.statistics((t or "").encode())[0] == brute_counts(t)


def test_rules_keep_and_reject(spark, docs, empty, labels):
    rows = [(k, sentence(k), None, None, 0) for k in range(60)] + [(100 + k, sentence(k).replace(" ", "%%% "), None, None, 0) for k in range(60)]
    frame = spark.createDataFrame(rows, DOCS)
    marks = spark.createDataFrame([(k, int(k < 100), 0) for k, *_ in rows if k % 2 == 0], "doc_id long, quality int, toxic int")
    trees = quality_rules.fit_rules(frame, marks)
    assert {r["doc_id"] for r in quality_rules.keep_good(frame, trees).collect()} == set(range(60))
    assert quality_rules.fit_rules(docs, labels) is None
    judged = quality_rules.judge(docs, None).collect()
    assert {r["doc_id"] for r in judged if r["base_failed"]} == {3, 4, 5, 7, 10, None}
    assert quality_rules.keep_good(docs, trees).columns == docs.columns
    assert quality_rules.judge(empty, trees).count() == quality_rules.keep_good(empty, trees).count() == 0


def test_trees_respect_directions():
    rnd = np.random.default_rng(0)
    x = rnd.random((600, 3))
    y = ((x[:, 0] - x[:, 1] + 0.3 * rnd.normal(size=600)) > 0).astype(float)
    trees = boosting.fit(x, y, np.array([1, -1, 0]))
    probe = rnd.random((50, 3))
    for column, sign in ((0, 1), (1, -1)):
        lines = np.repeat(probe, 21, axis=0)
        lines[:, column] = np.tile(np.linspace(0, 1, 21), 50)
        steps = np.diff(trees.margin(lines).reshape(50, 21), axis=1)
        assert (sign * steps >= -1e-12).all()
    assert ((trees.probability(x) > 0.5) == y).mean() > 0.8
    assert (boosting.fit(x, -y + 1, np.array([1, 1, 1]), trees=5).margin(x[:3]).shape) == (3,)


def test_samples_are_bounded_in_rows_and_bytes(spark):
    rows = [(7, f"version {k} " + "x" * 1000) for k in range(200)] + [(k, "y" * 100) for k in range(10, 60)] + [(99, None), (None, "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    marks = spark.createDataFrame([(r, 1) for r in [7, 7, *range(10, 60), 99, None]], "doc_id long, quality int")
    drawn = samples.labelled(docs, marks, "quality", 1000).collect()
    assert sorted(r["doc_id"] for r in drawn) == [7, *range(10, 60), 99]  # an id counts once
    assert samples.labelled(docs, marks, "quality", 1000).where("doc_id = 7").first()["text"] == next(r["text"] for r in drawn if r["doc_id"] == 7)
    few = samples.labelled(docs, marks, "quality", 1000, most_bytes=1500).collect()
    assert 1 <= len(few) < 20 and sum(len(r["text"] or "") for r in few) <= 1500
    assert len(samples.labelled(docs, marks, "quality", 5).collect()) == 5
    assert samples.labelled(docs.where("false"), marks, "quality", 5).count() == 0


def test_flat_trees_equal_a_walk_of_their_nodes():
    rnd = np.random.default_rng(4)
    x = rnd.random((400, 5))
    trees = boosting.fit(x, (x[:, 0] + x[:, 1] * x[:, 2] > 0.8).astype(float), np.array([1, 0, 0, -1, 0]), trees=15)

    def walked(row):
        total = trees.base
        for t in range(len(trees.feature)):
            node = 0
            while trees.feature[t, node] >= 0:
                node = trees.left[t, node] if row[trees.feature[t, node]] <= trees.threshold[t, node] else trees.right[t, node]
            total += trees.value[t, node]
        return total

    probe = np.concatenate([rnd.random((60, 5)), x[:60]])
    assert trees.margin(probe) == pytest.approx([walked(r) for r in probe])


def test_verdicts_equal_the_walk(spark):
    rows = [(k, sentence(k, 20) + (" %%% $$$" * (k % 4)), None, None, 0) for k in range(80)]
    frame = spark.createDataFrame(rows, DOCS)
    marks = spark.createDataFrame([(k, int(k % 4 < 2), 0) for k in range(80)], "doc_id long, quality int, toxic int")
    trees = quality_rules.fit_rules(frame, marks)
    for r in quality_rules.judge(frame, trees).collect():
        counts, features = quality_rules.statistics(rows[r["doc_id"]][1].encode())
        score = float(trees.probability(np.array([features]))[0])
        assert r["score"] == pytest.approx(score) and r["kept"] == (not r["base_failed"] and score >= 0.5) and r["n_words"] == counts[0]


# ----------------------------------------------------------------------- 4 toxicity


def test_toxicity_from_positive_and_unlabelled(spark, docs, empty, labels):
    rows, marks = [], []
    for k in range(600):
        bad = k % 4 == 0
        rows.append((k, sentence(k, 30) + (" vile wretched" if bad else ""), None, None, 0))
        if k // 4 % 2 == 0:
            marks.append((k, 1, int(bad)))
    frame = spark.createDataFrame(rows, DOCS)
    model = toxicity.fit_toxicity(frame, spark.createDataFrame(marks, "doc_id long, quality int, toxic int"))
    got = toxicity.score_documents(frame, model).collect()
    assert np.mean([(r["predicted"] == 1) == (r["doc_id"] % 4 == 0) for r in got if r["held_out"]]) > 0.97
    scored = toxicity.score_documents(docs, toxicity.fit_toxicity(docs, labels)).collect()
    assert len(scored) == len(EDGE)
    assert all(0 <= r["score"] <= 1 for r in scored)
    assert toxicity.score_documents(empty, model).count() == 0
    assert toxicity.score_documents(docs, toxicity.fit_toxicity(empty, labels.where("false"))).count() == len(EDGE)


def test_corrected_risk():
    pos, unl = np.array([2.0, -1.0]), np.array([0.5, 0.1, -0.4])
    loss = lambda z: np.log1p(np.exp(-z))
    up, down = toxicity.corrected_risk(pos, unl, 0.3)
    assert up == pytest.approx(0.3 * loss(pos).mean())
    assert down == pytest.approx(loss(-unl).mean() - 0.3 * loss(-pos).mean())


# ------------------------------------------------------------------------ 5 simhash


def brute_print(text, k=3):
    words = split_words("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + k]) for i in range(len(words) - k + 1)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(s.encode(), seed=42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(prints, radius, linked=None):
    linked = linked or (lambda a, b: (a ^ b).bit_count() <= radius)
    ids = list(range(len(prints)))
    root = dict(zip(ids, ids, strict=True))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for i in ids:
        for j in range(i):
            if linked(prints[i], prints[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in ids]


def test_near_duplicates_equal_brute_force(spark, small, docs, empty):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{small}/documents.parquet").collect()]
    rows += [(1000 + k, t) for k, t, *_ in EDGE if k is not None]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    got = simhash.near_duplicates(frame).collect()
    prints = [brute_print(t) for _, t in rows]
    comp = brute_components(prints, 2)
    low = {}
    for (d, _), c in zip(rows, comp, strict=True):
        low[c] = min(low.get(c, d), d)
    want = Counter((d, p, low[c]) for (d, _), p, c in zip(rows, prints, comp, strict=True))
    assert Counter((r["doc_id"], r["fp"] % (1 << 64), r["component_id"]) for r in got) == want
    assert simhash.near_duplicates(empty).count() == 0
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns
    ids = sorted(str(r["doc_id"]) for r in kept.collect())
    assert ids.count("7") == 1 and "2" not in ids and "None" in ids and "1" in ids
    assert ids.count("3") + ids.count("4") + ids.count("5") == 1


@pytest.mark.parametrize(("chunk", "rows"), [(2048, 1 << 20), (4, 0)])
def test_near_dedup_stage_links_every_pair_of_similar_texts(spark, chunk, rows, monkeypatch):
    monkeypatch.setattr(simhash, "BROADCAST_ROWS", rows)
    rnd = random.Random(5)
    texts = [sentence(500 + k, 120) for k in range(12)]
    for k in range(12):
        words = texts[k].split()
        words[20 + k] = "changed"  # 111 of 121 shingles are shared
        texts.append(" ".join(words))
        for at in rnd.sample(range(0, 120, 10), 5):
            words[at] = "other"
        texts.append(" ".join(words))
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in map(str.split, texts)]
    alike = [(a, b) for b in range(len(texts)) for a in range(b) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    far = [(a, b) for a, b in alike if (simhash.fingerprint(texts[a].encode()) ^ simhash.fingerprint(texts[b].encode())).bit_count() > 4]
    assert far  # four bits miss them
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    root = {r["doc_id"]: r["root"] for r in simhash.similar_groups(frame, chunk=chunk, few=chunk).collect()}
    assert all(root[a] == root[b] for a, b in alike) and len(set(root.values())) >= 12
    import corpus_pipeline

    kept = {r["doc_id"] for r in corpus_pipeline.near_dedup_stage(spark, frame, "").collect()}
    assert not [p for p in alike if kept.issuperset(p)]


@pytest.mark.parametrize(("radius", "chunk"), [(2, 2048), (2, 16), (4, 32)])
def test_links_of_crowded_buckets(spark, radius, chunk):
    rnd = random.Random(radius)
    centres = [rnd.getrandbits(64) for _ in range(4)]
    prints = {rnd.getrandbits(64) for _ in range(200)}
    for c in centres:
        for _ in range(90):
            p = c
            for b in rnd.sample(range(24), rnd.randrange(0, 6)):
                p ^= 1 << b
            prints.add(p)
    prints = sorted(prints)
    signed = [(p - (1 << 64) if p >> 63 else p,) for p in prints]
    frame = spark.createDataFrame(signed, "fp long")
    linked = simhash.components(simhash.links(frame, radius, chunk)).collect()
    root = {r["node"]: r["root"] for r in linked}
    label = [root.get(s[0], s[0]) for s in signed]
    comp = brute_components(prints, radius)
    assert len(set(label)) == len(set(comp)) == len(set(zip(label, comp, strict=True)))


def test_sets_of_one_similarity_share_a_key():
    rnd = np.random.default_rng(9)
    for n in [1, 2, 3, 5, 9, 10, 20, 31, 32, 33, 39, 40, 41, 45, 50, 51, 60, 300]:
        for _ in range(60):
            common = simhash.math.ceil(0.8 * n / 0.9)  # sizes n and up to 0.9 n, similar by 0.8 or more
            more = rnd.integers(0, 1 << 63, 4 * n + 8, dtype=np.uint64)
            a, b = np.unique(more[:n]), np.unique(np.concatenate([more[:common], more[n : n + max(0, int((n - common) * 0.2))]]))
            if len(np.intersect1d(a, b)) < 0.8 * len(np.union1d(a, b)):
                continue
            assert np.intersect1d(simhash.meeting_keys(a, 0.8), simhash.meeting_keys(b, 0.8)).size
    assert len(simhash.meeting_keys(np.arange(2000, dtype=np.uint64), 0.8)) == simhash.BANDS
    assert len(simhash.meeting_keys(np.zeros(0, np.uint64), 0.8)) <= 1


def test_bit_sliced_distances():
    rnd = np.random.default_rng(1)
    a = rnd.integers(0, 1 << 63, 130, dtype=np.uint64)
    b = a ^ (np.uint64(1) << rnd.integers(0, 63, 130).astype(np.uint64)) * rnd.integers(0, 3, 130).astype(np.uint64)
    exact = np.bitwise_count(a[:, None] ^ b[None])
    for radius in (0, 1, 2, 3, 7, 20):
        assert (simhash.sliced_matches(a, simhash.planes_of(b), radius, 130) == (exact <= radius)).all()
        assert (simhash.sliced_pairs(a, b, radius) == (np.diag(exact) <= radius)).all()


def test_components_of_a_long_path(spark):
    n = 60
    order = list(range(n))
    random.Random(0).shuffle(order)
    pairs = spark.createDataFrame(list(zip(order, order[1:], strict=False)), "a long, b long")
    assert {r["root"] for r in simhash.components(pairs).collect()} == {0}


# -------------------------------------------------------------- 6 quality classifier


def test_quality_machine(spark, docs, empty, labels):
    rows = [(k, sentence(k) if k % 3 else sentence(k).replace(" ", " | "), None, None, 0) for k in range(300)]
    frame = spark.createDataFrame(rows, DOCS)
    marks = spark.createDataFrame([(k, int(k % 3 > 0), 0) for k in range(300)], "doc_id long, quality int, toxic int")
    machine = quality_classifier.fit_quality(frame, marks)
    got = quality_classifier.score_documents(frame, machine).collect()
    assert all((r["predicted"] == 1) == (r["doc_id"] % 3 > 0) for r in got if r["held_out"])
    assert quality_classifier.score_documents(empty, machine).count() == 0
    edge = quality_classifier.score_documents(docs, quality_classifier.fit_quality(docs, labels)).collect()
    assert len(edge) == len(EDGE) and all(0 <= r["score"] <= 1 for r in edge)
    assert quality_classifier.score_documents(docs, quality_classifier.fit_quality(empty, labels.where("false"))).count() == len(EDGE)


def test_dual_descent_meets_its_conditions():
    import pyarrow as pa

    rnd = np.random.default_rng(3)
    x = [np.unique(rnd.integers(0, 40, 8)).astype(np.int32) for _ in range(120)]
    y = np.array([int((r < 12).sum() >= 3) for r in x], np.int32)
    rows = ngrams.Rows(pa.table({"y": pa.array(y), "x": pa.array(x, pa.list_(pa.int32()))}))
    scale = quality_classifier.log_count_ratio(rows)
    ones = rows.y == 1
    p = (1 + sum(7 in rows.row(k) for k in np.nonzero(ones)[0])) / (ones.sum() + 2)
    q = (1 + sum(7 in rows.row(k) for k in np.nonzero(~ones)[0])) / ((~ones).sum() + 2)
    assert scale[7] == pytest.approx(np.log(p / q))
    w, bias, alpha = quality_classifier.dual_descent(rows, np.ones(ngrams.SIZE), rounds=3000)
    sign = np.where(ones, 1, -1)
    unit = [1 / np.sqrt(len(rows.row(k))) for k in range(len(rows))]
    margin = np.array([w[rows.row(k)].sum() * unit[k] + bias for k in range(len(rows))])
    assert (sign * margin > 0).mean() > 0.85
    # the weights are those of the dual variables, which stay in their box, and both objectives agree
    bound = np.where(ones, len(rows) / (2 * ones.sum()), len(rows) / (2 * (~ones).sum()))
    made = np.zeros(ngrams.SIZE)
    for k in range(len(rows)):
        made[rows.row(k)] += alpha[k] * sign[k] * unit[k]
    assert np.abs(made - w).max() < 1e-9 and bias == pytest.approx((alpha * sign).sum())
    assert (alpha >= 0).all() and (alpha <= bound + 1e-12).all()
    size = (w @ w + bias * bias) / 2
    primal, dual = size + (bound * np.maximum(1 - sign * margin, 0)).sum(), alpha.sum() - size
    assert dual <= primal + 1e-9 and primal - dual < 0.01 * primal


# ---------------------------------------------------------------------------- 7 BPE


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(bpe.default_vocabulary())


PIECES = ["a", "aa", "th", "e", " ", "  ", "\n", "'s", "'ll", "1", "23", "é", "ß", "́", "中", "😀", "՘", " ", "_", "-", "...", "<|endoftext|>", "\x1c", "\x85", "\xa0", "ing", "ZZ", "٠", "²"]


def test_codec_equals_library(library):
    codec = bpe.compile_vocabulary(bpe.default_vocabulary())
    rnd = random.Random(5)
    texts = ["".join(rnd.choices(PIECES, k=rnd.randrange(60))) for _ in range(1500)]
    texts += ["", "a" * 4000, " " * 3000, "ab" * 2000, "-" * 999, "é" * 700, "\n\n\n", LONG] + [t or "" for _, t, *_ in EDGE]
    for t in texts:
        ids = library.encode(t, add_special_tokens=False).ids
        assert np.frombuffer(codec.encode(t), "<u4").tolist() == ids
        assert codec.decode(codec.encode(t)) == library.decode(ids, skip_special_tokens=False) == t


def test_automaton_equals_rewriting():
    letters = [bytes([97 + k]) for k in range(3)]
    rnd = random.Random(11)
    for _ in range(30):
        labels, merges = list(letters), []
        while len(labels) < 12:
            u, v = rnd.randrange(len(labels)), rnd.randrange(len(labels))
            if labels[u] + labels[v] not in labels:
                labels.append(labels[u] + labels[v])
                merges.append((u, v, len(labels) - 1))
        automaton = bpe.MergeAutomaton(labels, merges)
        for _ in range(60):
            word = bytes(rnd.choice(b"abc") for _ in range(rnd.randrange(1, 14)))
            tokens = [labels.index(bytes([b])) for b in word]
            while True:
                found = [(k, i) for k, (u, v, _) in enumerate(merges) for i in range(len(tokens) - 1) if (tokens[i], tokens[i + 1]) == (u, v)]
                if not found:
                    break
                k, i = min(found)
                tokens[i : i + 2] = [merges[k][2]]
            assert automaton.encode(word) == tokens


def test_words_walk_the_byte_table(library, monkeypatch):
    automaton = bpe.compile_vocabulary(bpe.default_vocabulary()).automaton
    words = [w.encode() for w in " believable| undoing|internationalisation|aaaaaaaaaaaaa| 中文é|<|endoftext|>|xqzjk".split("|")]
    first = [automaton.encode(w) for w in words]
    for w, ids in zip(words, first, strict=True):
        row = 0
        for k, byte in enumerate(w):  # the label of each row is the last token of the bytes so far
            row = automaton.table[row << 8 | byte]
            assert automaton.label[row] == library.encode(w[: k + 1].decode(errors="ignore"), add_special_tokens=False).ids[-1] or not w[: k + 1].isascii()
        assert automaton.label[row] == ids[-1]
    monkeypatch.setattr(automaton, "_enter", lambda *a: pytest.fail("a known word asked for a new entry"))
    monkeypatch.setattr(automaton, "_arc", lambda *a: pytest.fail("a known word asked for an arc"))
    assert [automaton.encode(w) for w in words] == first


@pytest.mark.parametrize("rows", [2, 3, 50])
def test_byte_table_starts_anew_inside_a_word(library, monkeypatch, rows):
    automaton = bpe.compile_vocabulary(bpe.default_vocabulary()).automaton
    word = "".join(random.Random(3).choices("abcdefghijklmnopqrstuvwxyz", k=900))
    monkeypatch.setattr(bpe, "ROWS", rows)
    assert automaton.encode(word.encode()) == library.encode(word, add_special_tokens=False).ids
    assert len(automaton.rows) <= rows + 2
    automaton.restart((0,), -1)


def test_other_vocabulary_files_are_refused():
    import json

    import public_tokenizers

    spec = json.loads(open(bpe.default_vocabulary(), encoding="utf-8").read())
    bpe.refuse_others(spec)
    with pytest.raises(ValueError, match="normalizers"):
        bpe.compile_vocabulary(public_tokenizers.path("word_bpe_49k.json"))
    for part, name, value in [("model", "ignore_merges", True), ("model", "end_of_word_suffix", "</w>"), ("pre_tokenizer", "add_prefix_space", True)]:
        with pytest.raises(ValueError, match=name):
            bpe.refuse_others(spec | {part: spec[part] | {name: value}})
    with pytest.raises(ValueError, match="lstrip"):
        bpe.refuse_others(spec | {"added_tokens": [spec["added_tokens"][0] | {"lstrip": True}]})


def test_encode_documents(spark, docs, empty, library):
    rows = bpe.encode_documents(docs, ["doc_id"]).collect()
    assert len(rows) == len(EDGE)
    for r in rows:
        assert len(r["ids"]) == r["n_tokens"]
        assert hashlib.sha256(np.array(r["ids"], "<u4").tobytes()).hexdigest() == r["ids_sha256"]
    assert {r["n_tokens"] for r in rows if r["doc_id"] in (3, 4)} == {0}
    assert bpe.encode_documents(empty, ["doc_id"]).count() == 0


# ------------------------------------------------------------------------- 8 mixing


def test_mix_meets_targets(spark, docs, empty):
    rnd = random.Random(2)
    rows = [(k, "w " * rnd.randrange(1, 60), None, f"s{rnd.choice([0, 0, 0, 1, 2])}" if k % 7 else None, 0) for k in range(900)]
    rows.append((5000, "w " * 3, None, "tiny", 0))
    out = mixing.mix(mixing.sized(spark.createDataFrame(rows, DOCS))).toPandas()
    assert len(out) == len(rows)
    assert (out["taken"] <= 3 * out["size"]).all()
    by = out.groupby(out["source"].fillna("~")).agg({"taken": "sum", "target": "first", "source_size": "first", "size": "sum"})
    assert (by["source_size"] == by["size"]).all()
    assert (abs(by["taken"] - by["target"]) <= 3).all()
    assert by.loc["tiny", "target"] == pytest.approx(9)
    assert by["target"].sum() == pytest.approx(out["size"].sum())
    again = mixing.mix(mixing.sized(spark.createDataFrame(rows[::-1], DOCS))).toPandas()
    assert sorted(zip(again["doc_id"], again["taken"], strict=True)) == sorted(zip(out["doc_id"], out["taken"], strict=True))
    assert mixing.mix(mixing.sized(docs)).count() == len(EDGE)
    assert mixing.mix(mixing.sized(empty)).count() == 0
    mixed = mixing.mixed_documents(docs)
    assert mixed.columns == docs.columns
    assert mixed.schema == docs.schema or [f.dataType for f in mixed.schema] == [f.dataType for f in docs.schema]


def dual_form(rows, want_a, want_b, cap):
    """Rates by plain alternating bisections on the two margins' variables."""
    a, b = {k: 0.0 for k in want_a}, {k: 0.0 for k in want_b}
    mass = lambda side, key: sum(n * min(cap, np.exp(a[i] + b[j])) for i, j, n in rows if (i, j)[side] == key)
    for _ in range(400):
        for side, table, want in ((0, a, want_a), (1, b, want_b)):
            for key in table:
                low, high = -30.0, 30.0
                for _ in range(80):
                    table[key] = (low + high) / 2
                    low, high = (table[key], high) if mass(side, key) < want[key] else (low, table[key])
    return {(i, j): min(cap, np.exp(a[i] + b[j])) for i, j, _ in rows}


def test_balance_solves_the_dual_with_its_cap(spark):
    rows = [(i, j, 10.0 * (1 + i) * (2 + j)) for i in range(3) for j in range(2)]
    cells = spark.createDataFrame([r for r in rows for _ in range(2)], "a int, b int, size double")
    want_a, want_b = {0: 250.0, 1: 130.0, 2: 150.0}, {0: 130.0, 1: 400.0}
    frame = lambda name, want: spark.createDataFrame(list(want.items()), f"{name} int, target double")
    got = mixing.balance(cells, "size", {"a": frame("a", want_a), "b": frame("b", want_b)}, cap=3).collect()
    assert max(r["gap"] for r in got) <= 1e-9
    rate = {(r["a"], r["b"]): r["rate"] for r in got}
    want = dual_form([(i, j, 2 * n) for i, j, n in rows], want_a, want_b, 3)
    assert rate == pytest.approx(want, abs=1e-6)
    assert max(rate.values()) == 3.0 and min(rate.values()) < 1  # the cap binds, inside the dual
    for k, t in want_a.items():
        assert sum(r["tokens"] * r["rate"] for r in got if r["a"] == k) == pytest.approx(t, rel=1e-9)
        size = sum(r["tokens"] for r in got if r["a"] == k)
        assert len({round(r["rate"], 6) for r in got if r["a"] == k}) > 1 and size  # no quotient of sums
    with pytest.raises(ValueError, match="constrained groups"):
        mixing.balance(cells, "size", {"a": frame("a", want_a), "b": frame("b", want_b)}, most=4)
    far = mixing.balance(cells, "size", {"a": frame("a", {0: 1e6, 1: 130.0, 2: 150.0}), "b": frame("b", want_b)}, rounds=30).first()
    assert far["gap"] > 0.1  # no rates meet these


def test_balance_of_one_margin_iterates(spark, monkeypatch):
    rows = [("x", 100.0), ("y", 40.0), (None, 10.0), ("free", 5.0), ("none", 8.0), ("full", 4.0), ("over", 4.0)]
    cells = spark.createDataFrame(rows, "s string, size double")
    goal = {"x": 250.0, "y": 1e-3, None: 11.0, "none": 0.0, "full": 12.0, "over": 99.0}
    want = spark.createDataFrame(list(goal.items()), "s string, target double")
    got = {r["s"]: r for r in mixing.balance(cells, "size", {"s": want}).collect()}
    plain = {"x": 2.5, "y": 2.5e-5, None: 1.1, "free": 1.0, "none": 0.0, "full": 3.0, "over": 3.0}
    assert {k: r["rate"] for k, r in got.items()} == pytest.approx(plain, rel=1e-11)
    assert got["x"]["gap"] == pytest.approx((99 - 12) / 99)
    # one Newton round from 1 is a tangent's step, not the quotient
    monkeypatch.setattr(mixing, "INNER", 1)
    short = {r["s"]: r["rate"] for r in mixing.balance(cells, "size", {"s": want}, rounds=1).collect()}
    assert short[None] == pytest.approx(np.exp(0.1)) and short["x"] == pytest.approx(np.e)


def test_one_id_on_many_rows_spreads_over_prefixes(spark, monkeypatch):
    monkeypatch.setattr(mixing, "PREFIX_ROWS", 1)
    rows = [(7 if k % 3 else None, f"w w w {k}", None, "a", 0) for k in range(600)]
    sizes = mixing.sized(spark.createDataFrame(rows, DOCS))
    spread = sizes.groupBy("source", "size", F.shiftright("digest", 50)).count().agg(F.max("count")).first()[0]
    assert spread < 12
    out = mixing.mix(sizes)
    assert out.count() == 600 and out.agg(F.sum("taken")).first()[0] == 2400


def test_mixing_stays_native(spark, small):
    plan = queries.op8_mixing(spark, small)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


# ------------------------------------------------------------------- 9 fingerprints


def test_gear_hash_by_doubling():
    data = np.frombuffer(LONG[:500].encode(), np.uint8)
    slow, h = [], 0
    for b in data.tolist():
        h = ((h << 1) + int(fingerprints.GEAR[b])) & 0xFFFFFFFF
        slow.append(h)
    assert fingerprints.gear_hashes(data).tolist() == slow


def test_chunks_resist_shifts():
    a = fingerprints.chunk_weights(LONG)
    b = fingerprints.chunk_weights("inserted words " + LONG[:5000] + " more " + LONG[5000:])
    assert fingerprints.containment(a, b) > 0.97
    assert fingerprints.containment(a, fingerprints.chunk_weights(sentence(77, 900))) < 0.1
    assert fingerprints.from_text(fingerprints.as_text(a)) == a
    sizes = np.diff([0, *fingerprints.boundaries(LONG.encode())])
    assert sizes[:-1].min() >= fingerprints.MIN and sizes.max() <= fingerprints.MAX and sizes.sum() == len(LONG.encode())
    assert fingerprints.containment({}, {}) == 1 and fingerprints.containment({}, a) == 0


def brute_chunks(text):
    """Chunk digests and their bytes, byte by byte."""
    data, out, start, h = text.encode(), {}, 0, 0
    hashes = []
    for byte in data:
        h = ((h << 1) + int(fingerprints.GEAR[byte])) & 0xFFFFFFFF
        hashes.append(h)
    while start < len(data):
        end = min(start + 256, len(data))
        if len(data) - start > 16:
            for k in range(start + 16, end + 1):
                bits = 8 if k - start < 64 else 4
                if hashes[k - 1] >> (32 - bits) == 0:
                    end = k
                    break
        digest = xxhash.xxh3_64_intdigest(data[start:end]) >> 16
        out[digest] = out.get(digest, 0) + end - start
        start = end
    return out


def brute_share(a, b):
    if not a:
        return 0.0 if b else 1.0
    return sum(min(n, b.get(d, 0)) for d, n in a.items()) / sum(a.values())


@pytest.mark.parametrize("buckets", [1, 3, 8, None])
def test_neighbours(spark, docs, empty, buckets, monkeypatch):
    inner = fingerprints.with_next
    monkeypatch.setattr(fingerprints, "with_next", lambda d: inner(d, buckets))
    rows = [(k * 3, sentence(k, 5 + 3 * k) + (" " + sentence(k - 1, 30)) * (k % 3), None, None, 0) for k in range(40)]
    rows += [(500, None, None, None, 0), (501, "", None, None, 0), (None, "last", None, None, 0)]
    got = {r["doc_id"]: r for r in fingerprints.neighbour_likeness(spark.createDataFrame(rows, DOCS)).collect()}
    order = sorted(rows, key=lambda r: -(r[0] if r[0] is not None else -1))
    for row, after in zip(order, order[1:] + order[:1], strict=True):
        text, nxt = row[1] or "", after[1] or ""
        half = len(text) // 2
        edited = text[: len(text) - half] + nxt[:half]
        r, own, other = got[row[0]], brute_chunks(text), brute_chunks(edited)
        assert r["n_chars"] == len(text)
        assert r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert fingerprints.from_text(r["fingerprint"]) == own
        assert fingerprints.from_text(r["edited_fingerprint"]) == other
        assert r["near_edited"] == pytest.approx(brute_share(own, other), abs=1e-12)
        assert r["near_next"] == pytest.approx(brute_share(own, brute_chunks(nxt)), abs=1e-12)
    assert fingerprints.neighbour_likeness(docs).count() == len(EDGE)
    assert fingerprints.neighbour_likeness(empty).count() == 0
    one = spark.createDataFrame([(4, "alone here", None, None, 0)], DOCS)
    assert fingerprints.neighbour_likeness(one).first()["near_next"] == 1.0
    assert fingerprints.fingerprint_documents(docs, ["doc_id"]).count() == len(EDGE)


def test_an_id_on_many_rows_is_split_over_buckets(spark):
    rows = [(k, f"own {k}", None, None, 0) for k in range(100)]
    rows += [(50, f"shared id {k}", None, None, 0) for k in range(300)] + [(None, f"no id {k}", None, None, 0) for k in range(200)]
    rows += [(50, "the same row", None, None, 0)] * 30
    frame = spark.createDataFrame(rows, DOCS)
    dealt = fingerprints.with_next(frame, 20)
    sizes = dealt.groupBy("bucket").agg(F.count_if(~F.col("ghost")).alias("n"), F.count_if("ghost").alias("ghosts")).collect()
    assert max(r["n"] for r in sizes) < 100 and len(sizes) > 15
    assert {r["ghosts"] for r in sizes} == {1}  # one ghost a bucket, whatever its repeats
    got = fingerprints.neighbour_likeness(frame).collect()
    assert len(got) == len(rows)
    tie = {t: v for t, v in frame.select("text", F.shiftrightunsigned(F.xxhash64("text"), 1)).collect()}
    order = sorted(rows, key=lambda r: (-(r[0] if r[0] is not None else -1), tie[r[1]]))
    want = Counter()
    for row, after in zip(order, order[1:] + order[:1], strict=True):
        half = len(row[1]) // 2
        want[row[0], hashlib.sha256((row[1][: len(row[1]) - half] + after[1][:half]).encode()).hexdigest()] += 1
    assert Counter((r["doc_id"], r["edited_sha256"]) for r in got) == want


# --------------------------------------------------------------------- 10 line dedup


def test_perfect_hash():
    rnd = np.random.default_rng(0)
    keys = np.unique(rnd.integers(0, 1 << 63, 5000, dtype=np.uint64))
    counts = rnd.integers(1, 1000, len(keys))
    shard = line_dedup.PerfectShard.load(line_dedup.PerfectShard.build(keys, counts).dump())
    assert sorted(shard.index(keys).tolist()) == list(range(len(keys)))
    assert (shard.lookup(keys) == counts).all()
    strangers = np.setdiff1d(rnd.integers(0, 1 << 63, 5000, dtype=np.uint64), keys)
    assert (shard.lookup(strangers) == 0).all()
    tight = line_dedup.PerfectShard.build(keys, counts, levels=2)
    assert (tight.lookup(keys) == counts).all()
    assert line_dedup.PerfectShard.build(keys[:0], counts[:0]).lookup(keys[:5]).tolist() == [0] * 5


def brute_lines(rows, least):
    strip = " \t\n\x0b\x0c\r"
    fold = lambda s: "".join(c.lower() if "A" <= c <= "Z" else c for c in s.strip(strip))
    found = Counter(k for t in rows for k in {fold(x) for x in (t or "").split("\n")} if k)
    out = []
    for t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if not (fold(x) and found[fold(x)] >= least)]
        out.append((len(lines), len(lines) - len(kept), "\n".join(kept)))
    return out


@pytest.mark.parametrize(("index_bytes", "shard_keys"), [(64 << 20, 32768), (64 << 20, 5), (1, 1 << 17), (1, 2)])
def test_lines_equal_brute_force(spark, docs, empty, index_bytes, shard_keys):
    texts = [f"Shared Line\n own {k}\n  shared line \r\nÉtat\n{'x' * (k % 3)}\n" for k in range(12)]
    texts += [f"pair {k // 2}\nrest {k}" for k in range(12)] + [None, "", "shared line", "\n\n", "état"] + [t for _, t, *_ in EDGE]
    frame = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string")
    kept = line_dedup.kept_lines(frame, min_docs=2, index_bytes=index_bytes, shard_keys=shard_keys)
    got = {r["row"]["doc_id"]: (r["added"]["n_lines"], r["added"]["n_dropped"], r["added"]["kept_text"]) for r in kept.collect()}
    assert [got[k] for k in range(len(texts))] == brute_lines(texts, 2)
    out = line_dedup.drop_common_lines(docs)
    assert out.columns == docs.columns and out.count() == len(EDGE)
    assert line_dedup.drop_common_lines(empty).count() == 0


@pytest.mark.parametrize("index_bytes", [64 << 20, 0])
def test_lines_count_documents_not_rows(spark, tmp_path, index_bytes):
    rows = [(7, f"told twelve times\nrow {k}") for k in range(12)]  # one document on many rows
    rows += [(100 + k, "told by ten\nelse") for k in range(9)] + [(109, "TOLD by ten  ")]
    rows += [(None, "no id\ntold by none")] * 15 + [(None, f"nameless {k}\ntold without ids") for k in range(10)]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    kept = line_dedup.kept_lines(frame, index_bytes=index_bytes)
    got = Counter((r["row"]["doc_id"], r["row"]["text"], r["added"]["kept_text"]) for r in kept.collect())
    gone = {"told by ten", "TOLD by ten  ", "told without ids"}
    want = Counter((d, t, "\n".join([x for x in t.split("\n") if x not in gone])) for d, t in rows)
    assert got == want
    frame.write.parquet(str(tmp_path / "documents.parquet"))
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{tmp_path}/documents.parquet/*.parquet'")
    twin = con.execute(queries.ORACLES["op10_line_dedup"]).fetchall()
    digest = lambda x: hashlib.sha256(x.encode()).hexdigest()
    drops = lambda t: sum(x in gone for x in t.split("\n"))
    assert Counter(twin) == Counter((d, t.count("\n") + 1, drops(t), digest("\n".join([x for x in t.split("\n") if x not in gone]))) for d, t in rows)


def test_line_probe_plans(spark, small):
    frame = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    plan = lambda size: line_dedup.kept_lines(frame, index_bytes=size)._jdf.queryExecution().executedPlan().toString()
    here, there = plan(64 << 20), plan(0)
    assert here.count("MapInArrow") == 1 and "Exchange" not in here
    assert there.count("MapInArrow") == 2 and "Exchange hashpartitioning(shard" in there


# ------------------------------------------------------------------ SQL and pipeline


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_sql_twin(spark, small, name):
    con = duckdb.connect()
    for t in ("documents", "conversations"):
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    got, want = queries.QUERIES[name](spark, small).toPandas(), con.execute(queries.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    plain = lambda f: f[sorted(f.columns)].round(6).astype(str).sort_values(sorted(f.columns)).values.tolist()
    assert plain(got) == plain(want)


def test_pipeline_equals_stage_by_stage_brute_force(spark, small, library):
    import corpus_pipeline

    got = corpus_pipeline.run(spark, small).toPandas()
    docs = spark.read.parquet(f"{small}/documents.parquet")
    trees = quality_rules.fit_rules(docs, spark.read.parquet(f"{small}/labels.parquet"))
    rows = [r for r in docs.collect() if r["doc_id"] in {k["doc_id"] for k in quality_rules.judge(docs, trees).where("kept").collect()}]
    different = sorted({r["text"] for r in rows})  # exact copies count once
    kept_text = dict(zip(different, [t for *_, t in brute_lines(different, 10)], strict=True))
    texts = {r["doc_id"]: kept_text[r["text"]] for r in rows}
    ids = sorted(texts)
    prints = [brute_print(texts[i]) for i in ids]
    shingles = [{tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set() for w in (split_words(texts[i].lower()) for i in ids)]
    alike = lambda a, b: len(shingles[a] & shingles[b]) >= 0.8 * len(shingles[a] | shingles[b])
    comp = brute_components(list(range(len(ids))), 0, lambda a, b: (prints[a] ^ prints[b]).bit_count() <= corpus_pipeline.RADIUS or alike(a, b))
    stay = [i for k, i in enumerate(ids) if comp[k] == k]
    source = {r["doc_id"]: r["source"] for r in rows}
    frame = spark.createDataFrame([(i, texts[i], source[i]) for i in stay], "doc_id long, text string, source string")
    copies = {r["doc_id"]: r["copies"] for r in mixing.mix(mixing.sized(frame)).collect()}
    want = Counter({i: copies[i] for i in stay if copies[i]})
    assert Counter(got["doc_id"].tolist()) == want
    for r in got.itertuples():
        assert list(r.ids) == library.encode(texts[r.doc_id], add_special_tokens=False).ids


def through(spark, frame, home):
    import corpus_pipeline

    for name, stage in corpus_pipeline.STAGES:
        stage(spark, frame, str(home)).write.parquet(str(home / name))
        frame = spark.read.parquet(str(home / name))
        yield name, frame


def test_stages_take_odd_rows_and_extra_columns(spark, docs, labels, tmp_path):
    labels.write.parquet(str(tmp_path / "labels.parquet"))
    got = dict(through(spark, docs, tmp_path))
    for name, frame in got.items():
        if name != "encoding":
            assert frame.columns == docs.columns
    ids = lambda name: sorted(str(r["doc_id"]) for r in got[name].collect())
    assert ids("quality_rules") == sorted(["1", "2", "6", "9"])  # the others have fewer than ten words
    assert ids("near_dedup") == sorted(["1", "6"]) or ids("near_dedup") == sorted(["1", "6", "9"])
    assert isinstance(got["encoding"].schema["ids"].dataType, T.ArrayType)


def test_stages_take_rows_without_ids(spark, labels, tmp_path):
    rows = [(None, sentence(k), None, None, None) for k in (1, 1, 2)] + [(5, sentence(3), None, "a", 1)] * 3 + [(6, None, None, "a", 0)]
    labels.write.parquet(str(tmp_path / "labels.parquet"))
    got = {name: sorted(str(r["doc_id"]) for r in f.collect()) for name, f in through(spark, spark.createDataFrame(rows, DOCS), tmp_path)}
    assert got["quality_rules"] == got["line_dedup"] == ["5"] * 3 + ["None"] * 3
    assert got["near_dedup"] == ["5"] + ["None"] * 3
    assert set(got["encoding"]) <= {"5", "None"}


def test_stages_take_empty_tables(spark, docs, labels, tmp_path):
    labels.where("false").write.parquet(str(tmp_path / "labels.parquet"))
    for name, frame in through(spark, docs.where("false"), tmp_path):
        assert frame.count() == 0, name


def test_line_stage_keeps_one_of_many_copies(spark):
    import corpus_pipeline

    text = "\n".join(sentence(40 + k, 15) for k in range(4))
    rows = [(k, text, None, "a", 1) for k in range(30)] + [(100 + k, f"shared by many\n{sentence(k, 20)}", None, "a", 1) for k in range(12)]
    frame = corpus_pipeline.line_dedup_stage(spark, spark.createDataFrame(rows, DOCS), "")
    kept = {r["doc_id"]: r["text"] for r in frame.collect()}
    assert all(kept[k] == text for k in range(30)) and all(kept[100 + k] == sentence(k, 20) for k in range(12))
    once = corpus_pipeline.near_dedup_stage(spark, frame, "").collect()
    assert sorted(r["doc_id"] for r in once if r["doc_id"] < 100) == [0]
