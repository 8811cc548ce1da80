"""Token store, packing, sharding, language model, near duplicates and the pipeline."""

from __future__ import annotations

import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from corpus_rows import prose

import corpus_pipeline
from tallgram.llm import language_model, near_dups, packing, sharding, token_store
from tallgram.llm.common import table
from tallgram.llm.tokens import Encoder, vocabulary_path

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def tokenizer():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(vocabulary_path())


def ids_of(tokenizer, text):
    return np.array([*tokenizer.encode(text or "", add_special_tokens=False).ids, 1], dtype="<u4")


def test_encoder_equals_the_tokenizer(tokenizer, edge_rows):
    import pyarrow as pa

    random.seed(3)
    alphabet = list("abzAZ .,!'\n\t\x0b09éÉ́İ<|>\x00日")
    texts = [r[1] for r in edge_rows] + ["".join(random.choices(alphabet, k=random.randint(0, 40))) for _ in range(400)] + ["Á J̌", "<|ENDOFTEXT|>", "x.,", "x'.", "...", "don't. we'll, I'S"]
    for part in (texts, texts[-3:], [t for t in texts if t and "<|" not in t and "́" not in t]):
        flat, offsets = Encoder.at(vocabulary_path()).encode(pa.array(part, pa.string()))
        for k, t in enumerate(part):
            assert flat[offsets[k] : offsets[k + 1]].tolist() == ids_of(tokenizer, t).tolist(), repr(t)


def by_id(rows):
    return sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0))


def test_token_store(spark, edge_docs, edge_rows, no_docs, tokenizer, tmp_path):
    got = by_id(tuple(r) for r in token_store.token_digests(edge_docs).collect())
    start, seen = 0, Counter()
    want = Counter((r[0], zlib.crc32(ids_of(tokenizer, r[1])), len(ids_of(tokenizer, r[1]))) for r in edge_rows)
    for doc, at, n, crc in sorted(got, key=lambda r: r[1]):
        assert at == start
        start += n
        seen[doc, crc, n] += 1
    assert seen == want
    assert token_store.token_digests(no_docs).count() == 0
    path = token_store.write_token_store(edge_docs, str(tmp_path / "store"))
    store = token_store.read_token_store(spark, path)
    asked = spark.createDataFrame([(3,), (108,), (999,), (None,), (3,)], "doc_id long")
    found = {r["doc_id"]: r["ids"] for r in token_store.fetch(store, asked).collect()}
    assert set(found) == {3, 108} and all(found[i] == ids_of(tokenizer, next(r[1] for r in edge_rows if r[0] == i)).tolist() for i in found)


def test_keyed_access_over_many_segments(spark, tokenizer, tmp_path, monkeypatch):
    """Ids that fill several segments, gaps between segments, and ids of every segment: one right row each."""
    monkeypatch.setattr(token_store, "SEGMENT_BYTES", 300)
    rows = [(i, prose(10, i)) for i in range(0, 300, 3)] + [(150, prose(40, 1000 + k)) for k in range(12)] + [(None, "none")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    store = token_store.read_token_store(spark, token_store.write_token_store(docs, str(tmp_path / "store")))
    assert store.count() > 10 and store.where("array_contains(doc_ids, 150)").count() > 1
    asked = spark.createDataFrame([(i,) for i in range(-5, 400)], "doc_id long")
    monkeypatch.setattr(token_store, "BROADCAST_IDS", 100)  # by shuffle
    plan = token_store.fetch(store, asked)
    assert "NestedLoop" not in plan._jdf.queryExecution().executedPlan().toString()
    out = plan.collect()
    texts = defaultdict(list)
    for i, t in rows:
        texts[i].append(ids_of(tokenizer, t).tolist())
    assert sorted(r["doc_id"] for r in out) == list(range(0, 300, 3))
    assert all(r["ids"] in texts[r["doc_id"]] for r in out)


@pytest.mark.parametrize("n", [0, 1, 2, 5, 100, 3000])
def test_perfect_hash(n):
    keys = token_store.key_hashes(list(range(n)))
    index = token_store.build_index(keys, np.arange(n) * 3, np.arange(n) % 7)
    known, row, first, count = token_store.lookup(index, keys)
    assert known.all() and (row == np.arange(n)).all() and (first == np.arange(n) * 3).all() and (count == np.arange(n) % 7).all()
    if n:
        stranger = token_store.lookup(index, token_store.key_hashes(list(range(10**6, 10**6 + 1000))))[0]
        assert stranger.sum() <= 1
    with pytest.raises(ValueError):
        token_store.build_index(np.array([5, 5], dtype=np.uint64), np.zeros(2), np.zeros(2))


def check_pieces(rows, texts, tokenizer):
    pieces, sequences = defaultdict(list), defaultdict(list)
    for r in rows:
        pieces[r["doc_id"], r["doc_tokens"]].append(r)
        sequences[r["sequence_id"]].append((r["offset"], r["length"]))
    total = 0
    for parts in sequences.values():
        at = 0
        for offset, n in sorted(parts):
            assert offset == at and n > 0
            at += n
        assert at <= packing.SEQUENCE
        total += at
    assert total == sum(len(ids_of(tokenizer, t)) for _, t in texts)
    known = defaultdict(list)
    for i, t in texts:
        known[i].append(ids_of(tokenizer, t))
    for (doc, n), parts in pieces.items():
        same = [x for x in known[doc] if len(x) == n]
        assert same and sum(p["length"] for p in parts) == n * len(same)
        if len(same) == 1:
            at = 0
            for p in sorted(parts, key=lambda p: p["start"]):
                assert p["start"] == at and p["ids_crc32"] == zlib.crc32(same[0][at : at + p["length"]])
                at += p["length"]
    return 1 - total / (packing.SEQUENCE * max(1, len(sequences)))


def test_packing(spark, edge_docs, edge_rows, no_docs, tokenizer):
    check_pieces(packing.pack_documents(edge_docs).collect(), [(r[0], r[1]) for r in edge_rows], tokenizer)
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    padding = check_pieces(packing.pack_documents(docs).collect(), [(r["doc_id"], r["text"]) for r in docs.collect()], tokenizer)
    assert padding < 0.01
    assert packing.pack_documents(no_docs).count() == 0


def test_packing_under_three_limits(spark):
    random.seed(1)
    rows = [(i, n := random.randint(1, 900), random.randint(0, n)) for i in range(3000)] + [(9001, 5000, 1), (9002, None, 1), (None, 10, 5)]
    limits = packing.Limits(2048, 6, 900)
    out = packing.pack_examples(spark.createDataFrame(rows, "example_id long, n_tokens long, loss_tokens long").coalesce(1), limits).collect()
    assert len(out) == len(rows)
    loads = defaultdict(lambda: [0, 0, 0])
    for r in out:
        if r["sequence_id"] is None:
            assert r["example_id"] in (9001, 9002)
            continue
        load = loads[r["sequence_id"]]
        for k, v in enumerate((r["n_tokens"], 1, r["loss_tokens"])):
            load[k] += v
    assert all(a <= 2048 and b <= 6 and c <= 900 for a, b, c in loads.values())
    best = max(sum(v[k] for v in loads.values()) / m for k, m in ((0, 2048), (1, 6), (2, 900)))
    assert len(loads) <= 1.15 * best + 1


def test_sharding(spark, edge_docs, edge_rows, no_docs):
    rows = sharding.shard_documents(edge_docs).collect()
    assert len(rows) == len(edge_rows)
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in rows) == Counter((r[0], len((r[1] or "").encode()) + 1, zlib.crc32((r[1] or "").encode())) for r in edge_rows)
    shards = defaultdict(list)
    for r in rows:
        shards[r["shard"]].append(r["slot"])
        assert r["law"] == "rows" and r["grown_shard"] is None
    assert sorted(shards) == list(range(8)) and max(map(len, shards.values())) - min(map(len, shards.values())) <= 1
    assert all(sorted(v) == list(range(len(v))) for v in shards.values())
    assert sharding.shard_documents(no_docs).count() == 0
    assert {r["shard"] for r in sharding.shard_documents(edge_docs.limit(3)).collect()} <= set(range(8))


def test_shards_match_the_mixture(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    counts = Counter((r["shard"], r["source"]) for r in sharding.shard_documents(docs).collect())
    for source in {s for _, s in counts}:
        share = [counts[k, source] for k in range(8)]
        assert max(share) - min(share) <= 1
    again = sharding.shard_documents(docs.repartition(5))
    assert sorted(map(tuple, again.collect()), key=str) == sorted(map(tuple, sharding.shard_documents(docs).collect()), key=str)


_TOKEN = re.compile(r"[^\x20\x09-\x0D]+")
_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def held(doc_id):
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % 7 == 2


def test_language_model_counts(edge_docs, edge_rows, no_docs):
    got = by_id(tuple(r) for r in language_model.scores(edge_docs).collect())
    counts, ends = Counter(), 0
    for r in edge_rows:
        if not held(r[0]):
            counts.update(_TOKEN.findall((r[1] or "").translate(_LOWER)))
            ends += 1
    n, v = sum(counts.values()) + ends, len(counts) + 1
    want = []
    for r in edge_rows:
        w = _TOKEN.findall((r[1] or "").translate(_LOWER))
        base = sum(math.log10((counts[x] + 1) / (n + v + 1)) for x in w) + math.log10((ends + 1) / (n + v + 1))
        want.append((r[0], held(r[0]), len(w) + 1, sum(counts[x] > 0 for x in w) + 1, n, round(base, 4)))
    assert sorted((*x[:5], round(x[5], 4)) for x in got if x[0] is not None) == sorted(x for x in want if x[0] is not None)
    assert all(x[6] < 0 for x in got)
    assert language_model.scores(no_docs).count() == 0


def test_language_model_beats_the_base_on_held_out_rows(spark):
    rows = [r for r in language_model.scores(table(spark, "/root/testdata/sf0.01", "documents")).collect() if r["held_out"]]
    assert sum(r["score"] for r in rows) > sum(r["base_score"] for r in rows) + 0.27 * sum(r["n_tokens"] for r in rows)


def plain_score(model, counts, words):
    """log10 probability of a text, word after word, every sum written out."""
    n, weights, total = model.classes.n, model.weights, 0.0
    earlier = before = n
    for w in [*words, None]:
        k = 0 if w is None else int(model.classes.of([w])[0])
        bucket = int(language_model._trigram(np.array([earlier * (n + 1) + before]))[0])
        x = [float(weights.bias[0][c]) + float(weights.before[before][c]) + float(weights.earlier[earlier][c]) + float(weights.pair[bucket][c]) for c in range(n)]
        top = max(x)
        total += (x[k] - top - math.log(sum(math.exp(v - top) for v in x))) / math.log(10)
        if k > len(model.classes.singles):
            own = [c for v, c in counts.items() if int(model.classes.of([v])[0]) == k]
            total += math.log10((counts.get(w, 0) + 1) / (sum(own) + len(own) + 1))
        earlier, before = before, k
    return total


def test_language_model_score_equals_a_plain_one(edge_docs, edge_rows, monkeypatch):
    monkeypatch.setattr(language_model, "SINGLES", 12)
    monkeypatch.setattr(language_model, "SHARED", 9)
    monkeypatch.setattr(language_model, "TOP", 20)
    monkeypatch.setattr(language_model, "CONTEXTS", 16)
    counts = Counter()
    for r in edge_rows:
        if not held(r[0]):
            counts.update(_TOKEN.findall((r[1] or "").translate(_LOWER)))
    model, _, _ = language_model.model_of(edge_docs)
    assert model.classes.n == 22 and sorted(model.top.values(), reverse=True) == sorted(counts.values(), reverse=True)[:20]
    texts = defaultdict(list)
    for r in edge_rows:
        words = _TOKEN.findall((r[1] or "").translate(_LOWER))
        if r[0] is not None and len(words) < 500:
            texts[r[0]].append(round(plain_score(model, counts, words), 3))
    got = defaultdict(list)
    for r in language_model.scores(edge_docs).collect():
        if r["doc_id"] in texts:
            got[r["doc_id"]].append(r["score"])
    for i, want in texts.items():
        assert np.allclose(sorted(got[i]), sorted(want), atol=2e-3), i


def test_language_model_is_a_distribution():
    """Class probabilities of every context add up to one, and so do words of a class with one unknown each."""
    rng = np.random.default_rng(1)
    n = 9
    w = language_model.Weights(rng.normal(size=(1, n)), rng.normal(size=(n + 1, n)), rng.normal(size=(n + 1, n)), rng.normal(size=(language_model.TRIGRAM_BUCKETS, n)))
    contexts = np.arange((n + 1) ** 2)
    assert np.allclose(np.exp(w.log_probabilities(contexts)).sum(axis=1), 1)
    every = np.repeat(contexts, n)
    assert np.allclose(w.of_tokens(every, np.tile(np.arange(n), len(contexts))).reshape(-1, n), w.log_probabilities(contexts))
    c = np.array([3.0, 5.0, 0.0])  # two known words and the unknown one
    logs = language_model.Model(language_model.Classes({}), w, np.array([0.0, 8.0]), np.array([0.0, 2.0]), 10, 3, 2, {}).word_logs(np.ones(3, dtype=int), c)
    assert np.isclose((10**logs).sum(), 1)


def test_training_rounds_raise_the_likelihood(spark, monkeypatch):
    rng = np.random.default_rng(2)
    n = 6
    rows = [(int(c), int(k), int(rng.integers(1, 50))) for c in range((n + 1) ** 2) for k in rng.choice(n, 3, replace=False)]
    cells = spark.createDataFrame(rows, "context long, class int, n long")
    weights, history = language_model.train(cells, n)
    assert all(b > a for a, b in zip(history, history[1:], strict=False))
    monkeypatch.setattr(language_model, "CONTEXTS", 5)  # in pieces: the same
    again, _ = language_model.train(cells, n)
    assert np.allclose(again.before, weights.before, atol=1e-4) and np.allclose(again.pair, weights.pair, atol=1e-4)


# --- near duplicates ---


def bag(text):
    w = re.findall(rb"[0-9a-z\x80-\xff]+", text.encode().lower())
    return Counter(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4) if w else 0))


def brute_classes(rows):
    nodes = {}
    for i, t in rows:
        if t is not None and i is not None:
            nodes[t] = min(nodes.get(t, i), i)
    bags = {i: bag(t) for t, i in nodes.items()}
    parent = {i: i for i in bags}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(bags)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            same, whole = sum((bags[a] & bags[b]).values()), sum((bags[a] | bags[b]).values())
            if whole and same >= 0.8 * whole:
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    return {(i, i if t is None else find(nodes[t])) for i, t in rows if i is not None}


def near_copies(n, seed, edits):
    random.seed(seed)
    base = prose(200, seed).split()
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(edits):
            w[random.randrange(len(w))] = random.choice("alpha beta gamma delta".split())
        out.append(" ".join(w))
    return out


def test_near_duplicates_equal_brute_force(spark, edge_docs, edge_rows, no_docs):
    got = {(r["doc_id"], r["class_id"]) for r in near_dups.near_duplicates(edge_docs).collect() if r["doc_id"] is not None}
    assert got == brute_classes([(r[0], r[1]) for r in edge_rows])
    assert near_dups.near_duplicates(no_docs).count() == 0
    # copies so far apart that a first member links to some of its group only
    texts = near_copies(60, 1, 4) + near_copies(30, 2, 2) + near_copies(20, 3, 0) + [prose(200, 50 + i) for i in range(30)]
    rows = list(enumerate(texts))
    random.shuffle(rows)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    out = near_dups.near_duplicates(docs).collect()
    assert {(r["doc_id"], r["class_id"]) for r in out} == brute_classes(rows)
    assert {r["doc_id"] for r in out if r["is_kept"]} == {c for _, c in brute_classes(rows)}


def test_one_row_for_each_id_and_hot_nodes(spark, monkeypatch):
    """Two texts of one id are one document; small bounds for hot nodes and chunks change nothing."""
    a, b = prose(80, 1), prose(80, 2)
    rows = [(1, a), (1, b), (2, a), (3, b), (4, None), (4, a), (5, None), (5, None), (6, b), (6, b), (None, a), (None, None)]
    got = near_dups.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(r["doc_id"] for r in got if r["doc_id"] is not None) == [1, 2, 3, 4, 5, 6] and len(got) == 8
    of = {r["doc_id"]: r["class_id"] for r in got}
    assert of[3] == of[6] and of[2] == of[4] and of[5] == 5 and of[2] != of[3] and of[1] in (of[2], of[3])
    kept = near_dups.keep_one_of_each_class(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(r["doc_id"] for r in kept if r["doc_id"] is not None) == sorted({c for c in of.values() if c is not None})
    monkeypatch.setattr(near_dups, "HOT_NODE", 3)
    monkeypatch.setattr(near_dups, "CHUNK", 2000)
    rows = list(enumerate(near_copies(50, 7, 4) + near_copies(20, 8, 1) + [prose(200, 70 + i) for i in range(10)]))
    out = near_dups.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {(r["doc_id"], r["class_id"]) for r in out} == brute_classes(rows)


def test_signatures_estimate_weighted_jaccard():
    random.seed(5)
    for share in (0.3, 0.6, 0.9):
        a = {random.getrandbits(60): random.randint(1, 9) for _ in range(300)}
        b = {k: v if random.random() < share else random.randint(1, 9) for k, v in a.items() if random.random() < 0.5 + share / 2}
        row = np.array([0] * len(a) + [1] * len(b))
        value = np.array([*a, *b], dtype=np.uint64)
        weight = np.array([*a.values(), *b.values()])
        s = near_dups.bag_signatures(row, value, weight, 2, 2000)
        true = sum(min(a.get(k, 0), b.get(k, 0)) for k in a) / sum(max(a.get(k, 0), b.get(k, 0)) for k in a)
        assert abs((s[0] == s[1]).mean() - true) < 0.05


def test_components_of_long_paths(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 105), (105, 101), (7, 7)]
    links = spark.createDataFrame(edges, "a long, b long")
    got = {r["node"]: r["component"] for r in near_dups.NearDuplicates(spark.createDataFrame([], "doc_id long, text string")).components(links).collect()}
    assert got == {**{i: 0 for i in range(1, 41)}, 105: 100, 101: 100}


# --- pipeline ---


def test_pipeline_stages(spark, tmp_path, tokenizer):
    from tallgram.llm import decontaminate, toxicity

    docs = table(spark, SMALL, "documents")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "toxicity", "near_duplicates", "decontamination", "packing"]
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SMALL)
        if name == "packing":
            break
        assert out.columns == docs.columns
        before, after = {r["doc_id"] for r in docs.collect()}, {r["doc_id"] for r in out.collect()}
        if name == "language":
            assert before - after == {r["doc_id"] for r in docs.collect() if not any(c.isalpha() for c in r["text"] or "")}
        if name == "toxicity":
            lexicon = toxicity.fit(docs, table(spark, SMALL, "labels"))
            assert after == {r["doc_id"] for r in docs.collect() if lexicon.score(r["text"]) < 0.5}
        if name == "near_duplicates":
            assert after == {c for _, c in brute_classes([(r["doc_id"], r["text"]) for r in docs.collect()])}
        if name == "decontamination":
            bad = decontaminate.contamination(docs, table(spark, SMALL, "benchmark")).where("contaminated").collect()
            assert after == before - {r["doc_id"] for r in bad}
        out.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
    packed = out.collect()
    assert check_pieces(packed, [(r["doc_id"], r["text"]) for r in docs.collect()], tokenizer) < 0.02
    # run() packs the same tokens of the same documents; which sequence holds a piece depends on how files are split
    whole = lambda rows: Counter((r["doc_id"], r["doc_tokens"]) for r in rows if not r["start"])
    again = corpus_pipeline.run(spark, SMALL).collect()
    assert whole(again) == whole(packed) and sum(r["length"] for r in again) == sum(r["length"] for r in packed)
    assert check_pieces(again, [(r["doc_id"], r["text"]) for r in docs.collect()], tokenizer) < 0.02


def test_pipeline_of_empty_tables(spark, no_docs, tmp_path):
    for name, columns in (("documents", no_docs.schema), ("labels", "doc_id long, quality int, toxic int"), ("benchmark", "item_id long, text string")):
        spark.createDataFrame([], columns).write.parquet(str(tmp_path / f"{name}.parquet"))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, no_docs, str(tmp_path))
        assert out.columns == no_docs.columns and out.count() == 0, name
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_pipeline_with_edge_rows(spark, edge_docs, edge_rows):
    docs = edge_docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, SMALL)
        assert docs.columns == edge_docs.columns
    kept = [r["doc_id"] for r in docs.collect()]
    assert sorted(i for i in kept if i is not None and 100 <= i <= 109) == [100, 106, 107, 108] and kept.count(None) == 1
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SMALL).count() >= len(kept)


def test_encoder_that_forgets_is_still_right(tokenizer, monkeypatch):
    import pyarrow as pa

    from tallgram.llm import tokens

    monkeypatch.setattr(tokens, "MEMORY", 40)
    encoder = Encoder(vocabulary_path())
    for part in range(6):
        texts = [prose(60, 10 * part + i) + f" new{part}word unseen{'abcdef'[part]}." for i in range(8)]
        flat, offsets = encoder.encode(pa.array(texts))
        for k, t in enumerate(texts):
            assert flat[offsets[k] : offsets[k + 1]].tolist() == ids_of(tokenizer, t).tolist()
    assert len(encoder.memory) < 200
