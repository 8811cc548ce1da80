"""Toxicity by a weighted lexicon (operator 10).

Texts are folded (case, look-alike letters, digits and signs that stand for
letters) and matched by one Aho-Corasick automaton over word starts, so an entry
is a whole word or the beginning of words. Where several entries match at one
word, the heaviest counts. Exception phrases take back what they cover. The sum of
weights, divided by a slowly growing function of the length, goes through a
logistic curve to a score from 0 to 1.

Weights are log-odds ratios of row counts over the labelled training rows
(``LABELLED_ROWS`` at most; equal texts count once), summed before the shuffle. An
entry needs toxic rows, evidence, and different neighbours in them: a rare word that
only copies of one text share is no lexicon entry. Exception phrases are learned as
well: pairs of neighbouring words of which one is an entry, but which clean rows use
at least as often as toxic ones.

Each labelled text is counted once, toxic ones first: clean ones then only count
entries that pass a filter of ``FILTER_BITS`` bits made of the toxic ones' entries (a
false positive is counted too and drops out of the sums). Then all are read to find
where entries match; from there on only the matches are looked at. Defined results: null and empty
texts have no match and get the score of no match; without toxic and clean labels no
entry is known, and every text gets that score; equal texts get equal scores.
Repeated label rows of one document count once, toxic if any says so.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.llm.common import blocks, split_rule, stored

#: Lengths of word beginnings that are tried as entries.
PREFIXES = (3, 4, 5, 6, 7, 8)
#: Toxic rows of an entry, and different pairs of neighbours in them, at least.
LEAST_ROWS, LEAST_CONTEXTS = 4, 4
LEAST_WEIGHT = 2.5
#: Likelihood-ratio statistic an entry needs: millions are tried, so chance gives values over 25 now and then.
LEAST_EVIDENCE = 26.0
#: Clean rows that a phrase needs to be an exception, and its log-odds ratio at most.
PHRASE_ROWS, PHRASE_WEIGHT = 3, 0.0
#: Labelled rows that are learned from at most (16 bytes each are broadcast).
LABELLED_ROWS = 1_000_000
#: Entries that a worker counts before it puts the counts out.
COUNTED = 500_000
#: Words whose entries a worker remembers.
REMEMBERED = 100_000
#: Size of the filter of entries; a power of two, whatever the size of the tables.
FILTER_BITS = 1 << 23
#: Characters that are folded at once; bounds the copies of a very long text.
FOLDED = 1 << 20

# fixed values: look-alike letters of other scripts, and signs that stand for letters
LOOKALIKES = {"а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "х": "x", "у": "y", "і": "i", "ѕ": "s", "ј": "j", "һ": "h", "ԁ": "d", "ԛ": "q", "ԝ": "w", "α": "a", "ο": "o", "ι": "i", "ν": "v", "κ": "k", "τ": "t", "ρ": "p", "в": "b", "н": "h", "м": "m", "т": "t", "к": "k", "ɡ": "g", "ⅼ": "l", "ı": "i", "ł": "l", "ø": "o"}
SIGNS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "i", "€": "e", "+": "t"}

_FULL_WIDTH = {chr(0xFF01 + i): chr(0x21 + i) for i in range(94)}
_FOLD = str.maketrans(_FULL_WIDTH | LOOKALIKES)
_FOLD_CODES = np.arange(0x110000, dtype="<u4")
_FOLD_CODES[list(_FOLD)] = [ord(c) for c in _FOLD.values()]
_WORD = re.compile(r"[^\W_]+")
_SIGNED = re.compile(r"(?<=[a-z])[0-9@$!|€+]+(?=[a-z])|(?<![^\W_])[0-9@$|€+]+(?=[a-z])")
_SIGN_TABLE = str.maketrans(SIGNS)
_BREAKS = {i: " " for i in range(128) if not chr(i).isalnum()}


def _letters(text: str) -> str:
    """Look-alike letters replaced, one by one."""
    codes = (np.frombuffer(text[i : i + FOLDED].encode("utf-32-le", "surrogatepass"), dtype="<u4") for i in range(0, len(text), FOLDED))
    return "".join(_FOLD_CODES[c].tobytes().decode("utf-32-le", "surrogatepass") for c in codes)


def fold(text: str | None) -> list[str]:
    """Folded words of a text."""
    if not text:
        return []
    text = text.lower()
    if not text.isascii():
        text = _letters(text)
    if any(c in text for c in SIGNS):
        text = _SIGNED.sub(lambda m: m[0].translate(_SIGN_TABLE), text)
    return text.translate(_BREAKS).split() if text.isascii() else _WORD.findall(text)


def normaliser(n_words: int) -> float:
    """Grows with the logarithm of the length, so that a few words in a long text still count."""
    return 1.0 + 0.15 * math.log1p(n_words / 100.0)


def _entries(word: str) -> list[str]:
    """Entry keys of a word: the word itself (ends in a blank) and its beginnings."""
    return [word + " ", *(word[:k] for k in PREFIXES if k < len(word))]


@dataclass
class Lexicon:
    """weights: entry to weight; an entry that ends in a blank is a whole word, others are beginnings."""

    weights: dict[str, float]
    exceptions: tuple[str, ...] = ()
    slope: float = 1.5
    bias: float = -2.0
    machine: ahocorasick.Automaton | None = field(default=None, repr=False, compare=False)

    def __getstate__(self) -> dict:
        return self.__dict__ | {"machine": None}

    def _machine(self) -> ahocorasick.Automaton:
        if self.machine is None:
            machine = ahocorasick.Automaton()
            for entry, w in self.weights.items():
                machine.add_word("\x01" + entry.replace(" ", "\x01"), (len(entry) + 1, w))
            for phrase in self.exceptions:
                key = "\x01" + "\x01".join(fold(phrase)) + "\x01"
                machine.add_word(key, (len(key), None))
            machine.make_automaton()
            self.machine = machine
        return self.machine

    def places(self, words: list[str]) -> list[tuple[int, float]]:
        """(word number, weight) of each match that counts: the heaviest entry of a word, none inside an exception phrase."""
        if not words or not self.weights:
            return []
        line = "\x01" + "\x01".join(words) + "\x01"
        best: dict[int, float] = {}
        free: list[tuple[int, int]] = []
        for end, (size, w) in self._machine().iter(line):
            start = end - size + 1
            if w is None:
                free.append((start, end))
            elif w > best.get(start, -1e9):
                best[start] = w
        if not best:
            return []
        begin = np.cumsum([0, *(len(w) + 1 for w in words)])
        covered = {s for s in best for a, b in free if a <= s < b}
        return [(int(np.searchsorted(begin, s)), w) for s, w in sorted(best.items()) if s not in covered]

    def matches(self, text: str | None) -> tuple[float, int, list[tuple[str, float]]]:
        """Sum of weights, number of words, and (folded word, weight) of each match that counts."""
        words = fold(text)
        found = [(words[i], w) for i, w in self.places(words)]
        return sum(w for _, w in found), len(words), found

    def feature(self, text: str | None) -> float:
        total, n, _ = self.matches(text)
        return total / normaliser(n)

    def score(self, text: str | None) -> float:
        return 1.0 / (1.0 + math.exp(-max(-40.0, min(40.0, self.slope * self.feature(text) + self.bias))))


def _labelled(docs: DataFrame, labels: DataFrame, labelled_rows: int) -> DataFrame:
    """doc_id, text, toxic of labelled rows that are not held out, one row of equal texts.

    Labels are small rows beside texts, so they are broadcast; labelled_rows bounds
    them (a hash of doc_id chooses which are used if there are more).
    """
    marks = labels.where("toxic is not null and doc_id is not null").where(~split_rule(5, 0)).groupBy("doc_id").agg(F.max("toxic").alias("_toxic"))
    n = marks.count()
    if n > labelled_rows:
        draw = F.shiftrightunsigned(F.xxhash64(F.lit(11), "doc_id"), 11) * F.lit(2.0**-53)
        marks = marks.where(draw < labelled_rows / n)
    texts = docs.select("doc_id", "text")
    marked = texts.join(F.broadcast(marks), "doc_id").select("doc_id", F.xxhash64("text").alias("_hash"), (F.col("_toxic") > 0).alias("toxic"))
    one = stored(marked.groupBy("_hash").agg(F.min("doc_id").alias("doc_id"), F.max("toxic").alias("toxic")), "labelled")
    # no more rows than marks, so bounded like them
    return texts.join(F.broadcast(one), "doc_id").where(F.xxhash64("text") == F.col("_hash")).select("doc_id", "text", "toxic")


def _put_out(counts: Counter, with_neighbours: bool) -> pa.RecordBatch:
    """The counts as a batch; they begin anew."""
    if with_neighbours:
        entry, around = zip(*counts, strict=True) if counts else ((), ())
        made = pa.RecordBatch.from_arrays([pa.array(entry, pa.string()), pa.array(around, pa.int64()), pa.array(counts.values(), pa.int64())], names=["entry", "around", "toxic"])
    else:
        made = pa.RecordBatch.from_arrays([pa.array(counts.keys(), pa.string()), pa.array(counts.values(), pa.int64())], names=["entry", "clean"])
    counts.clear()
    return made


def _count_toxic(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of each entry, with the neighbours of the entry's first place. The empty entry counts all rows."""
    counts: Counter = Counter()
    for batch in blocks(batches):
        for text in batch.column("text").to_pylist():
            words = fold(text)
            counts["", None] += 1
            first: dict[str, int] = {}
            for i in range(len(words) - 1, -1, -1):
                for e in _entries(words[i]):
                    first[e] = i
            for e, i in first.items():
                beside = ("" if not i else words[i - 1]) + " " + (words[i + 1] if i + 1 < len(words) else "")
                counts[e, zlib.crc32(beside.encode())] += 1
        if len(counts) > COUNTED:
            yield _put_out(counts, True)
    yield _put_out(counts, True)


def _filter(entries: DataFrame) -> np.ndarray:
    """FILTER_BITS bits, those of the entries' checksums set, as bytes; summed by Spark in words of 32 bits."""
    at = F.crc32(F.col("entry").cast("binary")) % FILTER_BITS
    words = entries.select(F.floor(at / 32).cast("int").alias("word"), F.pow(F.lit(2.0), at % 32).cast("long").alias("bit")).groupBy("word").agg(F.bit_or("bit").alias("bits")).toArrow()
    bits = np.zeros(FILTER_BITS // 32, dtype="<u4")
    bits[words.column("word").to_numpy()] = words.column("bits").to_numpy().astype("<u4")
    return bits.view(np.uint8)


def _clean_counts(rows: DataFrame, entries: DataFrame) -> DataFrame:
    """entry, clean: rows of each entry that passes the filter of the given entries. The empty entry counts all rows."""
    shared = rows.sparkSession.sparkContext.broadcast(_filter(entries).tobytes())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits, known, counts = shared.value, {}, Counter()
        for batch in blocks(batches):
            for text in batch.column("text").to_pylist():
                seen: set[str] = set()
                for word in set(fold(text)):
                    passed = known.get(word)
                    if passed is None:
                        if len(known) >= REMEMBERED:
                            known.clear()
                        at = [(e, zlib.crc32(e.encode("utf-8", "surrogatepass")) % FILTER_BITS) for e in _entries(word)]
                        passed = known[word] = tuple(e for e, k in at if bits[k >> 3] >> (k & 7) & 1)
                    seen.update(passed)
                counts[""] += 1
                counts.update(seen)
            if len(counts) > COUNTED:
                yield _put_out(counts, False)
        yield _put_out(counts, False)

    return rows.mapInArrow(run, "entry string, clean long").groupBy("entry").agg(F.sum("clean").alias("clean"))


def _phrases(words: list[str], i: int) -> list[str]:
    """The pairs of neighbouring words that hold word i."""
    return [" ".join(words[k : k + 2]) for k in (i - 1, i) if k >= 0 and k + 2 <= len(words)]


def _places(rows: DataFrame, lexicon: Lexicon) -> DataFrame:
    """toxic, rows, n_words, matches (weight, phrases) of rows with a match; rows without one are summed by label."""
    shared = rows.sparkSession.sparkContext.broadcast(lexicon)
    match = pa.list_(pa.struct([("weight", pa.float64()), ("phrases", pa.list_(pa.string()))]))
    schema = pa.schema([("toxic", pa.bool_()), ("rows", pa.int64()), ("n_words", pa.int64()), ("matches", match)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        none = {True: 0, False: 0}
        for batch in blocks(batches):
            found = []
            for text, toxic in zip(batch.column("text").to_pylist(), batch.column("toxic").to_pylist(), strict=True):
                words = fold(text)
                at = shared.value.places(words)
                if at:
                    found.append({"toxic": toxic, "rows": 1, "n_words": len(words), "matches": [{"weight": w, "phrases": _phrases(words, i)} for i, w in at]})
                else:
                    none[toxic] += 1
            yield pa.RecordBatch.from_pylist(found, schema=schema)
        yield pa.RecordBatch.from_pylist([{"toxic": t, "rows": n, "n_words": 0, "matches": []} for t, n in none.items() if n], schema=schema)

    return stored(rows.mapInArrow(run, "toxic boolean, rows long, n_words long, matches array<struct<weight:double,phrases:array<string>>>"), "matches")


def _log_odds(toxic, clean, n_toxic: int, n_clean: int):
    return F.log((toxic + 0.5) / F.lit(n_toxic + 1.0)) - F.log((clean + 0.5) / F.lit(n_clean + 1.0))


def fit(docs: DataFrame, labels: DataFrame, least_rows: int = LEAST_ROWS, labelled_rows: int = LABELLED_ROWS) -> Lexicon:
    """Learn entries, exception phrases and curve from the labelled rows that are not held out, labelled_rows at most."""
    rows = _labelled(docs, labels, labelled_rows)
    counted = rows.where("toxic").mapInArrow(_count_toxic, "entry string, around long, toxic long")
    of_toxic = counted.groupBy("entry").agg(F.sum("toxic").alias("toxic"), F.count_distinct("around").alias("around"))
    of_toxic = stored(of_toxic.where((F.col("entry") == "") | (F.col("toxic") >= least_rows) & (F.col("around") >= LEAST_CONTEXTS)), "toxic_entries")
    of_clean = _clean_counts(rows.where("not toxic"), of_toxic)
    sums = stored(of_toxic.join(of_clean, "entry", "left").fillna(0, ["clean"]), "entries")
    whole = sums.where("entry = ''").first()
    if whole is None or not whole["toxic"] or not whole["clean"]:
        return Lexicon({})
    n_toxic, n_clean = whole["toxic"], whole["clean"]
    weight = _log_odds(F.col("toxic"), F.col("clean"), n_toxic, n_clean)
    # entries that are as telling as that are few: each has least_rows of the labelled rows and hardly a clean one
    found = sums.where("entry != ''").withColumn("weight", weight).where(F.col("weight") >= LEAST_WEIGHT).select("entry", "toxic", "clean", "weight").toArrow()
    weights, counts = {}, {}
    for r in sorted(found.to_pylist(), key=lambda r: r["entry"]):
        if evidence(r["toxic"], r["clean"], n_toxic, n_clean) >= LEAST_EVIDENCE:
            weights[r["entry"]], counts[r["entry"]] = r["weight"], r["toxic"]
    lexicon = Lexicon(narrowed(weights, counts))
    places = _places(rows, lexicon)
    in_rows = places.select("toxic", F.explode(F.array_distinct(F.flatten(F.transform("matches", lambda m: m["phrases"])))).alias("phrase"))
    phrases = in_rows.groupBy("phrase").agg(F.count_if("toxic").alias("t"), F.count_if(~F.col("toxic")).alias("c")).where(F.col("c") >= PHRASE_ROWS)
    phrases = phrases.where(_log_odds(F.col("t"), F.col("c"), n_toxic, n_clean) <= PHRASE_WEIGHT)
    lexicon.exceptions = tuple(sorted(r["phrase"] for r in phrases.select("phrase").collect()))
    return _calibrated(places, lexicon)


#: Bins of the feature's logarithm over which the curve is fitted.
BINS_A_UNIT = 16


def evidence(a: int, b: int, n_toxic: int, n_clean: int) -> float:
    """Likelihood-ratio statistic of an entry in a of n_toxic and b of n_clean rows."""
    whole = n_toxic + n_clean

    def part(seen: float, expected: float) -> float:
        return seen * math.log(seen / expected) if seen else 0.0

    p = (a + b) / whole
    return 2 * (part(a, n_toxic * p) + part(b, n_clean * p) + part(n_toxic - a, n_toxic * (1 - p)) + part(n_clean - b, n_clean * (1 - p)))


def narrowed(weights: dict[str, float], counts: dict[str, int]) -> dict[str, float]:
    """Without beginnings that a longer entry explains: one with nine tenths of their toxic rows."""
    ordered = sorted(weights)
    kept = {}
    for i, entry in enumerate(ordered):
        j = i + 1
        while j < len(ordered) and ordered[j].startswith(entry):
            if counts[ordered[j]] >= 0.9 * counts[entry]:
                break
            j += 1
        else:
            kept[entry] = weights[entry]
            continue
        if j >= len(ordered) or not ordered[j].startswith(entry):
            kept[entry] = weights[entry]
    return kept


def _calibrated(places: DataFrame, lexicon: Lexicon) -> Lexicon:
    """Fit slope and bias on a histogram of the feature over all labelled rows, in bins of equal ratio."""
    free = set(lexicon.exceptions)
    shared = places.sparkSession.sparkContext.broadcast(free)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = [sum(m["weight"] for m in ms if not shared.value.intersection(m["phrases"])) / normaliser(n) for ms, n in zip(batch.column("matches").to_pylist(), batch.column("n_words").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("toxic"), batch.column("rows"), pa.array(x, pa.float64())], names=["toxic", "rows", "x"])

    values = places.mapInArrow(features, "toxic boolean, rows long, x double")
    bins = values.groupBy(F.floor(F.log1p("x") * BINS_A_UNIT).alias("bin"), "toxic").agg(F.sum("rows").alias("n"), F.sum(F.col("x") * F.col("rows")).alias("x"))
    found = sorted(bins.collect(), key=lambda r: (r["bin"], r["toxic"]))
    x = np.array([round(r["x"] / r["n"], 9) for r in found])
    y = np.array([float(r["toxic"]) for r in found])
    n = np.array([r["n"] for r in found], dtype=float)

    def loss(a: float, b: float) -> float:
        z = np.clip(a * x + b, -500, 500)
        return float((n * (np.logaddexp(0, z) - y * z)).sum() + 0.05 * a * a)

    a, b = 0.1, 0.0
    for _ in range(200):  # Newton steps, halved until they help
        p = 1 / (1 + np.exp(-np.clip(a * x + b, -40, 40)))
        g = np.array([(n * (p - y) * x).sum() + 0.1 * a, (n * (p - y)).sum()])
        s = n * p * (1 - p)
        h = np.array([[(s * x * x).sum() + 0.1, (s * x).sum()], [(s * x).sum(), s.sum() + 1e-3]])
        step, size, now = np.linalg.solve(h, g), 1.0, loss(a, b)
        while size > 1e-6 and loss(a - size * step[0], b - size * step[1]) > now:
            size /= 2
        if size <= 1e-6 or np.abs(step).max() < 1e-8:
            break
        a, b = a - size * step[0], b - size * step[1]
    if not (np.isfinite(a) and np.isfinite(b) and a > 0):
        return lexicon
    return Lexicon(lexicon.weights, lexicon.exceptions, float(a), float(b))


def scored(docs: DataFrame, lexicon: Lexicon) -> DataFrame:
    """doc_id, score, n_matches, worst (the heaviest matched word) of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in blocks(batches):
            score, count, worst = [], [], []
            for text in batch.column("text").to_pylist():
                total, n, found = model.matches(text)
                score.append(1.0 / (1.0 + math.exp(-max(-40.0, min(40.0, model.slope * total / normaliser(n) + model.bias)))))
                count.append(len(found))
                worst.append(max(found, key=lambda f: f[1])[0] if found else None)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(score), pa.array(count, pa.int32()), pa.array(worst, pa.string())], names=["doc_id", "score", "n_matches", "worst"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double, n_matches int, worst string")


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted, n_matches, worst of every document."""
    out = scored(docs, fit(docs, labels))
    return out.select("doc_id", split_rule(5, 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "n_matches", "worst")


def keep_clean(docs: DataFrame, lexicon: Lexicon, limit: float = 0.5) -> DataFrame:
    """Rows of docs, all columns, whose score is below limit."""
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            yield batch.filter(pa.array([shared.value.score(t) < limit for t in batch.column("text").to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
