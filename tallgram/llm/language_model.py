"""Language-model scores by a hashed maximum-entropy model (operator 6).

Words fall into classes: the most frequent words and the end of text have a class
of their own, all others share hashed classes by their last letters. The model is

    P(word | history) = P(class | history) * P(word | class).

P(class | history) is a softmax over the sum of weights of a bias, the class before
(bigram), the class two before (skip) and the hashed pair of both (trigram). It is
trained by rounds of distributed gradient steps: the corpus is summed up to counts
of (two classes before, class) once, partitions of contexts compute expected counts
of their features, the driver adds them up (model size, whatever the corpus) and
takes a preconditioned step. P(word | class) has add-one counts over all training
words, with one unknown word a hashed class, so every text has a probability and
they add up to one. Normalisers are made for the contexts that a block has, never
for all.

Word counts never meet in one place. Texts are turned once into blocks: a word
list, training counts, and token numbers. The ``TOP`` most frequent words, which
every block has, are broadcast with their counts; word lists of all others are
joined with the corpus counts and come back to their block as numbers, where numpy
scores all its texts. Blocks are dealt over as many tasks as their number asks for.

Defined results: null and empty texts have the end token alone; without training
rows N, V and all counts are 0 and score equals base_score; repeated rows are
scored each; equal texts get equal scores.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.llm.common import LOWER_BYTES, blocks, split_rule, stored, text_bytes

#: Frequent words with a class of their own, and hashed classes for the rest.
SINGLES, SHARED = 255, 256
TRIGRAM_BUCKETS = 2048
EPOCHS, RATE, PENALTY = 8, 0.6, 0.5
BLOCK_TEXT = 16 << 20
#: Partitions of contexts in training; contexts are bounded by the number of classes.
CONTEXT_PARTS = 8
#: Contexts whose softmax is made at once.
CONTEXTS = 2048
#: Frequent words whose counts are broadcast, and blocks a task scores.
TOP, BLOCKS_A_TASK = 65_536, 2

_BLOCKS = "block long, doc_ids array<bigint>, held array<boolean>, lengths array<int>, tokens binary, words array<string>, counts array<int>, train_docs long"
_SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double"


def _packed(numbers: np.ndarray) -> bytes:
    """int32 numbers as compressed byte planes."""
    planes = np.ascontiguousarray(numbers.astype("<i4").view(np.uint8).reshape(-1, 4).T)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def _unpacked(data: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), dtype=np.uint8).reshape(4, -1)
    return np.ascontiguousarray(planes.T).view("<i4").ravel()


def _read_block(batch: pa.RecordBatch) -> dict:
    raw, offsets = text_bytes(batch.column("text"))
    n = len(offsets) - 1
    texts = pa.LargeStringArray.from_buffers(n, pa.py_buffer(offsets.astype(np.int64)), pa.py_buffer(raw.translate(LOWER_BYTES)))
    lists = pc.ascii_split_whitespace(texts)
    flat = lists.flatten().dictionary_encode()
    bounds = lists.offsets.to_numpy() - lists.offsets[0].as_py()
    number, words = flat.indices.to_numpy().astype(np.int64), flat.dictionary
    full = pc.not_equal(pc.utf8_length(words), 0).to_numpy(zero_copy_only=False) if len(words) else np.zeros(0, dtype=bool)
    row = np.repeat(np.arange(n), np.diff(bounds))
    if len(full) and not full.all():  # the splitter leaves empty words at the ends of a text
        keep = full[number]
        number, row = (np.cumsum(full) - 1)[number[keep]], row[keep]
        words = words.filter(pa.array(full))
    held = batch.column("held").to_numpy(zero_copy_only=False).astype(bool)
    counts = np.bincount(number[~held[row]], minlength=len(words))
    return {"doc_ids": batch.column("doc_id").to_pylist(), "held": held.tolist(), "lengths": np.bincount(row, minlength=n).tolist(), "tokens": _packed(number), "words": words.to_pylist(), "counts": counts.tolist(), "train_docs": int((~held).sum())}


def _to_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    part = TaskContext.get().partitionId()
    schema = pa.schema([("block", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("held", pa.list_(pa.bool_())), ("lengths", pa.list_(pa.int32())), ("tokens", pa.binary()), ("words", pa.list_(pa.string())), ("counts", pa.list_(pa.int32())), ("train_docs", pa.int64())])
    waiting: list[pa.RecordBatch] = []
    size = serial = 0

    def out() -> pa.RecordBatch:
        whole = pa.Table.from_batches(waiting).combine_chunks().to_batches()[0]
        return pa.RecordBatch.from_pylist([{"block": (part << 24) + serial} | _read_block(whole)], schema=schema)

    for piece in blocks(batches, max_bytes=BLOCK_TEXT):
        n = pc.sum(pc.binary_length(piece.column("text"))).as_py() or 0
        if waiting and size + n > BLOCK_TEXT:
            yield out()
            waiting, size, serial = [], 0, serial + 1
        waiting.append(piece)
        size += n
    if waiting:
        yield out()


@dataclass
class Classes:
    """Class of each word: 0 is the end, then single words, then shared classes."""

    singles: dict[str, int]
    shared: int = SHARED

    @property
    def n(self) -> int:
        return 1 + len(self.singles) + self.shared

    def of(self, words: list[str]) -> np.ndarray:
        first, singles = 1 + len(self.singles), self.singles
        memory: dict[str, int] = {}
        out = np.empty(len(words), dtype=np.int32)
        for i, w in enumerate(words):
            k = singles.get(w)
            if k is None:
                tail = w[-2:]
                k = memory.get(tail)
                if k is None:
                    k = memory[tail] = first + zlib.crc32(tail.encode()) % self.shared
            out[i] = k
        return out


def _histories(classes: np.ndarray, lengths: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Class of each token with ends put in, and its context: (class two before) * (n + 1) + class before; n is the start."""
    many = lengths + 1
    ends = np.cumsum(many) - 1
    k = np.zeros(int(many.sum()), dtype=np.int64)
    inside = np.ones(len(k), dtype=bool)
    inside[ends] = False
    k[inside] = classes
    first = np.zeros(len(k), dtype=bool)
    first[ends - lengths] = True
    before = np.concatenate([[n], k[:-1]])
    before[first] = n
    earlier = np.concatenate([[n], before[:-1]])
    earlier[first] = n
    return k, earlier * (n + 1) + before


def _trigram(context: np.ndarray) -> np.ndarray:
    return (context.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)).astype(np.int64) % TRIGRAM_BUCKETS


@dataclass
class Weights:
    """Feature weights: bias (1 x n), before and earlier (n + 1 x n), pair (buckets x n)."""

    bias: np.ndarray
    before: np.ndarray
    earlier: np.ndarray
    pair: np.ndarray

    @property
    def n(self) -> int:
        return self.bias.shape[1]

    def features(self, context: np.ndarray) -> list[np.ndarray]:
        """The row of each weight table that a context uses."""
        return [np.zeros(len(context), dtype=np.int64), context % (self.n + 1), context // (self.n + 1), _trigram(context)]

    def tables(self) -> list[np.ndarray]:
        return [self.bias, self.before, self.earlier, self.pair]

    def log_probabilities(self, context: np.ndarray) -> np.ndarray:
        """ln P(class | context), contexts x classes."""
        x = self.bias + sum(t[f] for t, f in zip(self.tables()[1:], self.features(context)[1:], strict=True))
        x -= x.max(axis=1, keepdims=True)
        x -= np.log(np.exp(x).sum(axis=1, keepdims=True))
        return x

    def of_tokens(self, context: np.ndarray, klass: np.ndarray) -> np.ndarray:
        """ln P(class | context) of each token, the softmax made once for each context."""
        known, at = np.unique(context, return_inverse=True)
        order = np.argsort(at, kind="stable")
        bounds = np.searchsorted(at[order], np.arange(0, len(known) + CONTEXTS, CONTEXTS))
        out = np.empty(len(context))
        for k, (a, b) in enumerate(zip(bounds[:-1], bounds[1:], strict=True)):
            mine = order[a:b]
            out[mine] = self.log_probabilities(known[k * CONTEXTS : (k + 1) * CONTEXTS])[at[mine] - k * CONTEXTS, klass[mine]]
        return out


def _cells(blocks_df: DataFrame, classes: Classes) -> DataFrame:
    """context, class, n over all training tokens: summed in blocks, then in tasks, then over the corpus."""
    shared = blocks_df.sparkSession.sparkContext.broadcast(classes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        for batch in batches:
            for row in batch.to_pylist():
                k = known.of(row["words"])[_unpacked(row["tokens"])]
                lengths, held = np.array(row["lengths"], dtype=np.int64), np.array(row["held"], dtype=bool)
                k = k[~np.repeat(held, lengths)]
                k, context = _histories(k, lengths[~held], known.n)
                cell, many = np.unique(context * known.n + k, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(cell // known.n), pa.array((cell % known.n).astype(np.int32)), pa.array(many)], names=["context", "class", "n"])

    found = blocks_df.select("lengths", "held", "tokens", "words").mapInArrow(run, "context long, class int, n long")
    return found.groupBy("context", "class").agg(F.sum("n").alias("n"))


def _add_rows(table: np.ndarray, row: np.ndarray, values: np.ndarray) -> None:
    """table[row] += values, rows that repeat added one after another."""
    while len(row):
        _, first = np.unique(row, return_index=True)
        table[row[first]] += values[first]
        if len(first) == len(row):
            return
        rest = np.ones(len(row), dtype=bool)
        rest[first] = False
        row, values = row[rest], values[rest]


def _expected(weights: Weights, context: np.ndarray, klass: np.ndarray, many: np.ndarray) -> tuple[float, list[np.ndarray]]:
    """Log-likelihood of cells, and the expected count of each feature and class.

    Contexts of one class before are taken together: no two of them have one class
    two before, so their expected counts are added to rows that hardly repeat.
    """
    order = np.lexsort([context, context % (weights.n + 1)])
    context, klass, many = context[order], klass[order], many[order]
    new = np.ones(len(context), dtype=bool)
    new[1:] = context[1:] != context[:-1]
    begin = np.flatnonzero(new)
    known, total = context[begin], np.add.reduceat(many, begin)
    group = known % (weights.n + 1)
    bounds = [*np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])).tolist(), len(known)]
    cells = [*begin.tolist(), len(context)]
    sums = [np.zeros(t.shape) for t in weights.tables()]
    likelihood = 0.0
    for a, b in zip(bounds[:-1], bounds[1:], strict=True):
        logs = weights.log_probabilities(known[a:b])
        low, high = cells[a], cells[b]
        likelihood += float((many[low:high] * logs[np.cumsum(new[low:high]) - 1, klass[low:high]]).sum())
        np.exp(logs, out=logs)
        logs *= total[a:b, None].astype(logs.dtype)
        whole = logs.sum(axis=0, dtype=np.float64)
        _, _, earlier, pair = weights.features(known[a:b])
        sums[0][0] += whole
        sums[1][group[a]] += whole
        sums[2][earlier] += logs
        _add_rows(sums[3], pair, logs)
    return likelihood, sums


def train(cells: DataFrame, n: int, epochs: int = EPOCHS) -> tuple[Weights, list[float]]:
    """Weights and the mean log-likelihood before each round. cells: context, class, n."""
    spark = cells.sparkSession
    part = F.pmod(F.xxhash64(F.pmod("context", F.lit(n + 1))), F.lit(CONTEXT_PARTS))  # by the class before
    cells = stored(cells.withColumn("part", part).repartition(CONTEXT_PARTS, "part").select("context", "class", "n"), "cells")
    weights = Weights(np.zeros((1, n), np.float32), np.zeros((n + 1, n), np.float32), np.zeros((n + 1, n), np.float32), np.zeros((TRIGRAM_BUCKETS, n), np.float32))
    shapes = [t.shape for t in weights.tables()]
    history: list[float] = []
    observed: list[np.ndarray] = []
    total = 0.0
    for epoch in range(epochs + 1):
        shared = spark.sparkContext.broadcast(weights)

        def gradient(batches: Iterator[pa.RecordBatch], shared=shared, first=not epoch) -> Iterator[pa.RecordBatch]:
            got = [b for b in batches if b.num_rows]
            if not got:
                return
            whole = pa.Table.from_batches(got)
            context, klass, many = (whole.column(c).to_numpy() for c in ("context", "class", "n"))
            w = shared.value
            likelihood, expected = _expected(w, context, klass, many.astype(np.float64))
            seen = [np.bincount(f * n + klass, weights=many, minlength=t.size) for f, t in zip(w.features(context), w.tables(), strict=True)] if first else []
            pack = lambda parts: np.concatenate([p.ravel() for p in parts]).astype("<f4").tobytes() if parts else b""
            yield pa.RecordBatch.from_pylist([{"likelihood": likelihood, "total": float(many.sum()), "expected": pack(expected), "observed": pack(seen)}])

        found = cells.mapInArrow(gradient, "likelihood double, total double, expected binary, observed binary").toArrow()
        shared.unpersist()

        def tables(name: str, found=found) -> list[np.ndarray]:
            flat, out = np.zeros(sum(a * b for a, b in shapes)), []
            for part in found.column(name):
                flat += np.frombuffer(part.as_buffer(), dtype="<f4")
            for a, b in shapes:
                out.append(flat[: a * b].reshape(a, b))
                flat = flat[a * b :]
            return out

        if not epoch:
            observed, total = tables("observed"), sum(found.column("total").to_pylist())
        history.append(sum(found.column("likelihood").to_pylist()) / max(1.0, total))
        if epoch == epochs or not total:
            break
        # observed minus expected, scaled by expected counts; the first step alone sets bias and bigrams
        for kind, (table, obs, ex) in enumerate(zip(weights.tables(), observed, tables("expected"), strict=True)):
            if epoch == 0 and kind == 0:
                table += np.log((obs + 1.0) / (obs.sum() + n))
            elif epoch == 0:
                continue
            elif epoch == 1 and kind == 1:
                table += np.log((obs + PENALTY) / (ex + PENALTY))
            elif epoch > 1 or kind == 1:
                table += RATE * np.clip((obs - ex - 0.01 * table) / (ex + 2.0), -1.0, 1.0) / (1 if kind else 4)
    return weights, history


@dataclass
class Model:
    classes: Classes
    weights: Weights
    class_tokens: np.ndarray
    class_words: np.ndarray
    tokens: int  # N
    words: int  # V
    end_count: int
    top: dict[str, int]  # counts of the most frequent words

    def word_logs(self, k: np.ndarray, c: np.ndarray) -> np.ndarray:
        """log10 P(word | class) of words with training count c."""
        single = k <= len(self.classes.singles)
        return np.where(single, 0.0, np.log10((c + 1.0) / (self.class_tokens[k] + self.class_words[k] + 1.0)))


def fit(blocks_df: DataFrame, counts: DataFrame) -> tuple[Model, list[float]]:
    """The model of all training rows. counts: word, c (c > 0)."""
    docs = blocks_df.agg(F.sum("train_docs").alias("n")).first()["n"] or 0
    total = counts.agg(F.sum("c").alias("n"), F.count("*").alias("v")).first()
    top = {r["word"]: r["c"] for r in counts.orderBy(F.desc("c"), "word").limit(TOP).collect()}
    classes = Classes({w: i + 1 for i, w in enumerate(list(top)[:SINGLES])}, SHARED)
    shared = counts.sparkSession.sparkContext.broadcast(classes)

    def by_class(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, v = np.zeros(shared.value.n, dtype=np.int64), np.zeros(shared.value.n, dtype=np.int64)
        for batch in batches:
            k = shared.value.of(batch.column("word").to_pylist())
            n += np.bincount(k, weights=batch.column("c").to_numpy(), minlength=len(n)).astype(np.int64)
            v += np.bincount(k, minlength=len(v))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(n))), pa.array(n), pa.array(v)], names=["class", "n", "v"])

    sums = counts.mapInArrow(by_class, "class long, n long, v long").groupBy("class").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).collect()
    class_tokens, class_words = np.zeros(classes.n), np.zeros(classes.n)
    for r in sums:
        class_tokens[r["class"]], class_words[r["class"]] = r["n"], r["v"]
    weights, history = train(_cells(blocks_df, classes), classes.n)
    return Model(classes, weights, class_tokens, class_words, int((total["n"] or 0) + docs), int(total["v"] + (docs > 0)), int(docs), top), history


def _score_block(model: Model, block: pa.Table, known: pa.Table) -> pa.Table:
    """Scores of the documents of one block; known: idx, c of its words that training has, but for the most frequent."""
    rows = block.to_pylist()
    out = []
    for row in rows:
        c = np.fromiter((model.top.get(w, 0) for w in row["words"]), dtype=np.float64, count=len(row["words"]))
        c[known.column("idx").to_numpy()] = known.column("c").to_numpy()
        token, lengths = _unpacked(row["tokens"]), np.array(row["lengths"], dtype=np.int64)
        k = model.classes.of(row["words"])
        doc = np.repeat(np.arange(len(lengths)), lengths)
        whole = model.tokens + model.words + 1.0
        base = np.bincount(doc, weights=np.log10((c + 1.0) / whole)[token], minlength=len(lengths)) + np.log10((model.end_count + 1.0) / whole)
        n_known = np.bincount(doc, weights=(c > 0)[token], minlength=len(lengths)) + (model.end_count > 0)
        score = base
        if model.tokens:
            sequence, context = _histories(k[token], lengths, model.classes.n)
            step = model.weights.of_tokens(context, sequence) / np.log(10.0)
            at = np.repeat(np.arange(len(lengths)), lengths + 1)
            score = np.bincount(at, weights=step, minlength=len(lengths)) + np.bincount(doc, weights=model.word_logs(k, c)[token], minlength=len(lengths))
        out.append(pa.table({"doc_id": pa.array(row["doc_ids"], pa.int64()), "held_out": pa.array(row["held"]), "n_tokens": pa.array(lengths + 1), "n_known": pa.array(n_known.astype(np.int64)), "base_score": pa.array(base), "score": pa.array(score)}))
    return pa.concat_tables(out) if out else pa.table({"doc_id": pa.array([], pa.int64()), "held_out": pa.array([], pa.bool_()), "n_tokens": pa.array([], pa.int64()), "n_known": pa.array([], pa.int64()), "base_score": pa.array([], pa.float64()), "score": pa.array([], pa.float64())})


def model_of(docs: DataFrame) -> tuple[Model, DataFrame, DataFrame]:
    """The model of the training rows of docs, the stored blocks of all rows, and the stored word counts."""
    made = stored(docs.select("doc_id", "text", split_rule(7, 2).alias("held")).mapInArrow(_to_blocks, _BLOCKS), "blocks")
    entries = made.select(F.explode(F.arrays_zip("words", "counts")).alias("e")).select(F.col("e.words").alias("word"), F.col("e.counts").alias("n")).where("n > 0")
    counts = stored(entries.groupBy("word").agg(F.sum("n").alias("c")), "counts")
    return fit(made, counts)[0], made, counts


def scores(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every document."""
    spark = docs.sparkSession
    model, made, counts = model_of(docs)
    frequent = spark.createDataFrame([(w,) for w in model.top], "word string")  # TOP rows at most
    listed = made.select("block", F.posexplode("words").alias("idx", "word")).join(F.broadcast(frequent), "word", "left_anti")
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-made.count() // BLOCKS_A_TASK))
    known = listed.join(counts, "word").select(F.col("block").alias("of_block"), "idx", "c").repartition(tasks, "of_block")
    held = made.select("block", "doc_ids", "held", "lengths", "tokens", "words").repartition(tasks, "block")
    shared = spark.sparkContext.broadcast(model)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        return _score_block(shared.value, left, right)

    scored = held.groupBy("block").cogroup(known.groupBy("of_block")).applyInArrow(run, _SCORES)
    return scored.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(model.tokens).cast("long").alias("train_tokens"), "base_score", "score")
