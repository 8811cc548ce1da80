"""Language identification by hierarchical discrimination (operator 2).

First the language family is told, then the language inside the family. Both
levels use linear support vector machines, one for each pair of classes, over
hashed byte n-grams of the whole lower-cased text; the class with the largest sum
of margins over its pairs wins. Weights come from a bounded sample of labelled
rows (``per_language`` rows of each language, chosen by a hash of doc_id);
prediction scores every byte of every text with array look-ups.

Defined results: texts that are null or hold no letter are ``und`` with score 0;
with no labelled row all are ``und``; with one known language all others texts are
that language with score 1. Equal texts get equal results.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.llm.common import blocks, split_rule, text_bytes

BUCKETS = 1 << 13
ORDERS = (2, 3, 4)
PER_LANGUAGE = 800

#: fixed values: families of ISO 639-1 codes; a code that isn't here is a family of its own
FAMILIES = {
    "germanic": "en de nl sv da no nb nn is af fy lb yi",
    "romance": "fr es it pt ro ca gl oc",
    "slavic": "ru uk be pl cs sk bg sr hr sl mk bs",
    "turkic": "tr az kk ky uz tk tt",
    "indic": "hi bn ur mr gu pa ne si",
    "semitic": "ar he mt am",
    "uralic": "fi et hu",
    "celtic": "ga gd cy br",
    "baltic": "lt lv",
}
_FAMILY = {code: name for name, codes in FAMILIES.items() for code in codes.split()}


def family_of(lang: str) -> str:
    return _FAMILY.get(lang.lower().split("-")[0], lang)


_LETTERS = bytes(i + 32 if 65 <= i <= 90 else i if 97 <= i <= 122 or i >= 128 else 32 for i in range(256))


def _folded(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Lower-case bytes with all but letters blank, and row offsets; Latin-1 capitals are lowered too."""
    raw, offsets = text_bytes(column)
    data = np.frombuffer(raw.translate(_LETTERS), dtype=np.uint8).copy()
    after_c3 = np.zeros(len(data), dtype=bool)
    after_c3[1:] = data[:-1] == 0xC3
    data[after_c3 & (data >= 0x80) & (data <= 0x9E)] += 0x20
    return data, offsets


def _grams(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of the n-grams at each place (places x orders), BUCKETS where there is none; rows of places."""
    n = len(data)
    out = np.full((n, len(ORDERS)), BUCKETS, dtype=np.int32)
    value = np.zeros(n, dtype=np.uint32)
    to_end = np.repeat(offsets[1:], np.diff(offsets)) - np.arange(n)
    previous_blank = np.ones(n, dtype=bool)
    previous_blank[1:] = data[:-1] == 32
    empty = previous_blank & (data == 32)  # only the first blank of a run starts n-grams
    x = data.astype(np.uint32)
    for k in range(max(ORDERS)):
        value[: n - k] = value[: n - k] * np.uint32(0x01000193) + x[k:] + np.uint32(1)
        if k + 1 in ORDERS:
            h = value * np.uint32(0x9E3779B1)
            col = ORDERS.index(k + 1)
            out[:, col] = ((h ^ (h >> np.uint32(15))) + np.uint32(k * 0x51ED)) % np.uint32(BUCKETS)
            out[(to_end < k + 1) | empty, col] = BUCKETS
    return out, to_end


def has_letters(column: pa.Array, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Which rows hold a letter; only rows with no ASCII letter are looked at one by one."""
    run = np.concatenate([[0], np.cumsum((data >= 97) & (data <= 122))])
    some = run[offsets[1:]] > run[offsets[:-1]]
    for i in np.flatnonzero(~some & (np.diff(offsets) > 0)):
        some[i] = any(c.isalpha() for c in column[int(i)].as_py() or "")
    return some


@dataclass
class Model:
    """Weights of the pairwise machines: columns of ``weights`` (BUCKETS + 1 rows, the last one zeros)."""

    classes: list[str]
    families: list[str]
    pairs: list[tuple[str, str, str]]  # level ("" for families, else the family), first class, second class
    weights: np.ndarray
    bias: np.ndarray
    slope: np.ndarray

    def __post_init__(self) -> None:
        self.columns = [np.ascontiguousarray(self.weights[:, p]) for p in range(self.weights.shape[1])]

    def predict(self, column: pa.Array) -> tuple[list[str], np.ndarray]:
        n = len(column)
        data, offsets = _folded(column)
        letters = has_letters(column, data, offsets)
        if not self.classes:
            return ["und"] * n, np.zeros(n)
        step = 1 << 18
        grams = np.zeros(n)
        sums = np.zeros((n, len(self.pairs)))
        for low, high in _row_runs(offsets, step):
            part = data[offsets[low] : offsets[high]]
            if not len(part):
                continue
            at, _ = _grams(part, offsets[low : high + 1] - offsets[low])
            local = offsets[low:high] - offsets[low]
            filled = np.flatnonzero(np.diff(offsets[low : high + 1]) > 0)
            if not len(filled):
                continue
            for column in range(len(ORDERS)):
                where = np.ascontiguousarray(at[:, column])
                grams[low + filled] += np.add.reduceat(where < BUCKETS, local[filled], dtype=np.int64)
                for p in range(len(self.pairs)):
                    sums[low + filled, p] += np.add.reduceat(np.take(self.columns[p], where), local[filled], dtype=np.float64)
        margins = sums / np.maximum(grams, 1)[:, None] * SCALE + self.bias
        out, score = np.full(n, "und", dtype=object), np.zeros(n)
        rows = np.flatnonzero(letters)
        family, sure = self._vote("", self.families, margins[rows])
        for f in range(len(self.families)):
            mine = rows[family == f]
            if len(mine):
                inside = [c for c in self.classes if family_of(c) == self.families[f]]
                which, sure_inside = self._vote(self.families[f], inside, margins[mine])
                out[mine] = np.array(inside, dtype=object)[which]
                score[mine] = sure[family == f] * sure_inside
        return out.tolist(), np.clip(score, 0.0, 1.0)

    def _vote(self, level: str, classes: list[str], margins: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Class with the most one-versus-one votes (margins break ties) and how sure its pairs are of it."""
        n, k = len(margins), len(classes)
        votes, total, least = np.zeros((n, k)), np.zeros((n, k)), np.ones((n, k))
        for p, (where, a, b) in enumerate(self.pairs):
            if where != level:
                continue
            i, j, m = classes.index(a), classes.index(b), margins[:, p]
            votes[:, i] += m >= 0
            votes[:, j] += m < 0
            total[:, i] += m
            total[:, j] -= m
            sure = 1 / (1 + np.exp(-np.clip(self.slope[p] * m, -40, 40)))
            least[:, i], least[:, j] = np.minimum(least[:, i], sure), np.minimum(least[:, j], 1 - sure)
        best = np.argmax(votes + 1e-3 * np.tanh(total), axis=1) if k else np.zeros(n, dtype=int)
        return best, least[np.arange(n), best]


#: Features are shares of n-grams times this, so that margins are near one.
SCALE = 30.0


def _row_runs(offsets: np.ndarray, step: int) -> Iterator[tuple[int, int]]:
    low, n = 0, len(offsets) - 1
    while low < n:
        high = max(low + 1, int(np.searchsorted(offsets, offsets[low] + step, side="right")) - 1)
        yield low, min(high, n)
        low = min(high, n)


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """lang, buckets and counts of each labelled text (whole text)."""
    for batch in blocks(batches, max_bytes=2 << 20):
        data, offsets = _folded(batch.column("text"))
        at, _ = _grams(data, offsets)
        index, count = [], []
        for a, b in zip(offsets[:-1], offsets[1:], strict=True):
            found, n = np.unique(at[a:b].ravel(), return_counts=True)
            keep = found < BUCKETS
            index.append(found[keep])
            count.append(n[keep])
        yield pa.RecordBatch.from_arrays([batch.column("lang"), pa.array(index, pa.list_(pa.int32())), pa.array(count, pa.list_(pa.int32()))], names=["lang", "index", "count"])


def _svm(x: np.ndarray, y: np.ndarray, epochs: int = 20, penalty: float = 1e-4) -> tuple[np.ndarray, float]:
    """A linear support vector machine by mini-batch subgradient steps of decreasing length; classes weigh alike."""
    random = np.random.Generator(np.random.PCG64(5))
    w, bias = np.zeros(x.shape[1], dtype=np.float32), 0.0
    mean, mean_bias, steps = np.zeros_like(w), 0.0, 0
    weight = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y < 0).sum())) * len(y)
    size, t = 64, 0
    for epoch in range(epochs):
        order = random.permutation(len(y))
        for low in range(0, len(y), size):
            rows = order[low : low + size]
            t += 1
            rate = 0.5 / (1 + 0.01 * t)
            off = y[rows] * (x[rows] @ w + bias) < 1
            pull = (weight[rows] * y[rows])[off]
            w *= 1 - rate * penalty
            if off.any():
                w += rate / len(rows) * (pull @ x[rows[off]]).astype(np.float32)
                bias += rate / len(rows) * float(pull.sum())
            if epoch >= epochs // 2:
                mean += w
                mean_bias += bias
                steps += 1
    return (mean / max(1, steps)).astype(np.float32), mean_bias / max(1, steps)


def fit(labelled: DataFrame, per_language: int = PER_LANGUAGE) -> Model:
    """Fit on rows (doc_id, text, lang); per_language bounds the sample of each language."""
    labelled = labelled.select("doc_id", "text", "lang").where("lang is not null and text is not null")
    have = {r["lang"]: r["n"] for r in labelled.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    classes = sorted(have)
    if not classes:
        return Model([], [], [], np.zeros((BUCKETS + 1, 0), np.float32), np.zeros(0), np.zeros(0))
    share = F.create_map(*[v for c, n in have.items() for v in (F.lit(c), F.lit(min(1.0, per_language / n)))])
    draw = F.shiftrightunsigned(F.xxhash64(F.lit(7), "doc_id"), 11) * F.lit(2.0**-53)
    rows = labelled.where(draw < share[F.col("lang")]).mapInArrow(_features, "lang string, index array<int>, count array<int>").toArrow()
    lang = np.array(rows.column("lang").to_pylist(), dtype=object)
    x = np.zeros((len(lang), BUCKETS), dtype=np.float32)
    for i, (index, count) in enumerate(zip(rows.column("index"), rows.column("count"), strict=True)):
        x[i, index.values.to_numpy()] = count.values.to_numpy()
    x *= SCALE / np.maximum(1, x.sum(axis=1, keepdims=True))
    families = sorted({family_of(c) for c in classes})
    family = np.array([family_of(c) for c in lang], dtype=object)
    tasks = [("", a, b, family) for a, b in combinations(families, 2)]
    tasks += [(f, a, b, lang) for f in families for a, b in combinations([c for c in classes if family_of(c) == f], 2)]
    weights = np.zeros((BUCKETS + 1, len(tasks)), dtype=np.float32)
    bias, slope = np.zeros(len(tasks)), np.ones(len(tasks))
    for p, (_, a, b, of) in enumerate(tasks):
        rows_of = np.flatnonzero((of == a) | (of == b))
        y = np.where(of[rows_of] == a, 1.0, -1.0)
        if len(np.unique(y)) < 2:
            bias[p] = 1.0 if (y > 0).any() else -1.0
            continue
        weights[:BUCKETS, p], bias[p] = _svm(x[rows_of], y)
        margin = y * (x[rows_of] @ weights[:BUCKETS, p] + bias[p])
        grid = np.array([0.5, 1, 2, 3, 4, 6, 8])  # slope of the margin-to-probability curve, by likelihood
        slope[p] = grid[int(np.argmin([np.log1p(np.exp(-np.clip(s * margin, -40, 40))).mean() for s in grid]))]
    return Model(classes, families, [t[:3] for t in tasks], weights, bias, slope)


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred, score of every row. The model is a few hundred kilobytes, whatever the corpus."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            lang, score = shared.value.predict(batch.column("text"))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(lang, pa.string()), pa.array(score)], names=["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double")


def training_rows(docs: DataFrame) -> DataFrame:
    """Rows that may be learned from: a known language, and not held out."""
    return docs.where(~split_rule(4, 2) & F.col("lang").isNotNull())


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every document."""
    out = predict(docs, fit(training_rows(docs)))
    return out.select("doc_id", split_rule(4, 2).alias("held_out"), "lang_pred", "score")


def keep_identified(docs: DataFrame) -> DataFrame:
    """Rows of docs, all columns, whose text has a language (``und`` texts go)."""
    shared = docs.sparkSession.sparkContext.broadcast(fit(training_rows(docs)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            lang, _ = shared.value.predict(batch.column("text"))
            yield batch.filter(pa.array([x != "und" for x in lang]))

    return docs.mapInArrow(run, docs.schema)
