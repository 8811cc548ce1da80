"""Near-duplicate documents by BagMinHash signatures (operator 9).

A document is the bag of its five-word shingles; similarity is weighted Jaccard,
the sum of smaller multiplicities over the sum of larger ones. The weight axis of
every shingle is cut into dyadic levels (0,1], (1,2], (2,4], ...; each level of
each shingle is a Poisson process of points, each with a time, a register and a
position on the axis, and points above the shingle's weight don't count. A register
keeps the earliest time. Processes depend only on shingle and level, so a register
of two bags agrees with probability equal to their weighted Jaccard similarity.
Points are made in order of time up to a bound that fills all registers, so the
work for a bag is proportional to its shingles once, not to registers times
shingles.

Registers form bands; documents that share a band are candidates. In a band's
group every member is compared with the group's pivot first, as many pairs as
members; the pivot is the member that meets most others over all its bands, which
for copies with edits is the text they come from. Groups whose members then still
lie in several components are taken up again: the members outside the largest
component are compared with all others, in blocks of bounded size, so that no link
between documents that share a band is lost. Every candidate pair is verified on
exact multiset overlap.

Classes are the connected components of verified links. Copies (equal texts) are
joined to one node before all that, wherever a third of all rows is one text. Nodes
of many links are dealt over several tasks in the rounds that find components.

Defined results: null texts are alone in their class; texts without words form
classes with their exact copies only; shorter texts than five words have one
shingle of all their words; rows of one doc_id are one document with one row in the
result, whose text is the one with the smallest digest.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tallgram.llm.common import Words, blocks, mix64, stored, trim

SHINGLE = 5
THRESHOLD = 0.8
BANDS, ROWS = 26, 5
#: Shingles of one side in a task that compares the rest of a group.
CHUNK = 120_000
#: Links of a node from which on its links are dealt over several tasks.
HOT_NODE = 2_000
#: Rows up to which a side of ids is broadcast (16 bytes a row); beyond it both sides are shuffled.
BROADCAST_ROWS = 1_000_000

_GOLD = np.uint64(0x9E3779B97F4A7C15)


def shingle_hashes(words: Words, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of every shingle of a block; a text of fewer words, but some, is one shingle."""
    h = words.hashes()
    n = len(h)
    first = np.cumsum(words.per_row) - words.per_row
    place = np.arange(n) - first[words.row]
    many = np.where(words.per_row >= size, words.per_row - size + 1, np.minimum(words.per_row, 1))
    start = place < many[words.row]
    at = np.flatnonzero(start)
    last = (first + words.per_row)[words.row[at]]
    out = np.zeros(len(at), dtype=np.uint64)
    for k in range(size):
        here = at + k
        inside = here < last
        value = np.where(inside, h[np.minimum(here, max(0, n - 1))], np.uint64(0)) if n else out
        out = out * np.uint64(0xD1342543DE82EF95) + value + np.uint64(k + 1)
    return words.row[at], mix64(out)


def bags(row: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, shingle, multiplicity) of each distinct shingle of each row, ordered by row."""
    order = np.lexsort([value, row])
    row, value = row[order], value[order]
    new = np.ones(len(row), dtype=bool)
    new[1:] = (row[1:] != row[:-1]) | (value[1:] != value[:-1])
    begin = np.flatnonzero(new)
    return row[begin], value[begin], np.diff(np.append(begin, len(row)))


def _unit(x: np.ndarray) -> np.ndarray:
    """Uniform in (0, 1]."""
    return ((x >> np.uint64(11)).astype(np.float64) + 1.0) * 2.0**-53


def bag_signatures(row: np.ndarray, value: np.ndarray, weight: np.ndarray, n_rows: int, m: int) -> np.ndarray:
    """Registers (n_rows x m, uint64; 0 for rows without shingles) of bags given as (row, shingle, weight)."""
    total = np.bincount(row, weights=weight, minlength=n_rows)
    # dyadic levels of each shingle's weight axis: level 0 is (0,1], level l is (2^(l-1), 2^l]
    levels = np.ceil(np.log2(np.maximum(weight, 1))).astype(np.int64) + 1
    source = np.repeat(np.arange(len(row)), levels)
    level = np.arange(levels.sum()) - np.repeat(np.cumsum(levels) - levels, levels)
    process = mix64(value[source] + (level + 1).astype(np.uint64) * _GOLD)
    width = np.where(level == 0, 1.0, np.exp2(np.maximum(level - 1, 0)))
    base = np.where(level == 0, 0.0, np.exp2(np.maximum(level - 1, 0)))
    time = np.zeros((n_rows, m))
    best = np.full((n_rows, m), np.inf)
    tag = np.zeros((n_rows, m), dtype=np.uint64)
    todo = total > 0
    bound = np.zeros(n_rows)
    bound[todo] = (np.log(m) + 4.0) / total[todo]
    del time
    while todo.any():
        live = np.flatnonzero(todo[row[source]])
        p, who, at = process[live], row[source[live]], np.zeros(len(live))
        w, low, span = weight[source[live]], base[live], width[live]
        step = 0
        while len(p):
            step += 1
            draw = mix64(p + np.uint64(step * 0xA0761D6478BD642F & 0xFFFFFFFFFFFFFFFF))
            at = at - np.log(_unit(draw)) / (m * span)
            keep = at <= bound[who]
            p, who, at, w, low, span, draw = p[keep], who[keep], at[keep], w[keep], low[keep], span[keep], draw[keep]
            if not len(p):
                break
            more = mix64(draw ^ np.uint64(0xE7037ED1A0B428DB))
            position = low + _unit(mix64(more + _GOLD)) * span
            counts = np.ceil(position) <= w  # positions count by unit steps: weights are whole numbers
            cell = who[counts] * m + (more[counts] % np.uint64(m)).astype(np.int64)
            order = np.lexsort([at[counts], cell])
            cell, when, mark = cell[order], at[counts][order], more[counts][order]
            first = np.ones(len(cell), dtype=bool)
            first[1:] = cell[1:] != cell[:-1]
            cell, when, mark = cell[first], when[first], mark[first]
            better = when < best.ravel()[cell]
            best.ravel()[cell[better]] = when[better]
            tag.ravel()[cell[better]] = mark[better]
        open_rows = np.flatnonzero(todo)
        full = np.isfinite(best[open_rows]).all(axis=1)
        todo[open_rows[full]] = False
        again = open_rows[~full]
        bound[again] *= 2
        best[again] = np.inf
    return tag


def band_keys(signature: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """One 64-bit key for each band of each row."""
    out = np.zeros((len(signature), bands), dtype=np.uint64)
    for b in range(bands):
        key = np.full(len(signature), b + 1, dtype=np.uint64)
        for r in range(rows):
            key = mix64(key * _GOLD + signature[:, b * rows + r])
        out[:, b] = key
    return out


def _signed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """doc_id, a 128-bit text hash, shingle count and band keys."""
    import xxhash

    for batch in blocks(batches, max_bytes=2 << 20, owner="words"):
        texts = batch.column("text")
        words = Words(texts)
        row, value, many = bags(*shingle_hashes(words))
        keys = band_keys(bag_signatures(row, value, many, batch.num_rows, BANDS * ROWS)).view(np.int64)
        size = np.bincount(row, weights=many, minlength=batch.num_rows).astype(np.int64)
        digest = [None if t is None else xxhash.xxh3_128_digest(t.encode()) for t in texts.to_pylist()]
        empty = size == 0
        lists = pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(np.where(empty, 0, BANDS))]).astype(np.int32), pa.array(keys[~empty].ravel()))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(digest, pa.binary()), pa.array(size), lists], names=["doc_id", "digest", "size", "bands"])


def _shingle_lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """node and shingles; the k-th copy of a shingle has a value of its own, so sets of values are bags."""
    import xxhash

    for batch in blocks(batches, max_bytes=2 << 20, owner="words"):
        pairs = zip(batch.column("text").to_pylist(), batch.column("digest").to_pylist(), strict=True)
        batch = batch.filter(pa.array([xxhash.xxh3_128_digest(t.encode()) == d for t, d in pairs], pa.bool_()))  # another text of the id
        if not batch.num_rows:
            continue
        row, value, many = bags(*shingle_hashes(Words(batch.column("text"))))
        source = np.repeat(np.arange(len(row)), many)
        copy = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        values = np.where(copy == 0, value[source], mix64(value[source] + copy.astype(np.uint64) * _GOLD))
        counts = np.bincount(row[source], minlength=batch.num_rows)
        lists = pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32), pa.array(values.view(np.int64)))
        yield pa.RecordBatch.from_arrays([batch.column("node"), lists], names=["node", "shingles"])


def _bounded(small: DataFrame, n: int) -> DataFrame:
    """small with a broadcast hint if it has so few rows that it is sure to fit."""
    return F.broadcast(small) if n <= BROADCAST_ROWS else small


def _overlaps(batches: Iterator[pa.RecordBatch], threshold: float) -> Iterator[pa.RecordBatch]:
    """Pairs whose bags reach the threshold."""
    for batch in batches:
        left, right = batch.column("left"), batch.column("right")
        keep, similarity = [], []
        for i in range(batch.num_rows):
            a, b = left[i].values.to_numpy(), right[i].values.to_numpy()
            same = len(np.intersect1d(a, b, assume_unique=True))
            j = same / max(1, len(a) + len(b) - same)
            if j >= threshold:
                keep.append(i)
                similarity.append(j)
        kept = batch.take(pa.array(keep, pa.int64()))
        yield pa.RecordBatch.from_arrays([kept.column("a"), kept.column("b"), pa.array(similarity, pa.float64())], names=["a", "b", "similarity"])
        del batch, left, right, kept
    trim()


def _rest_of_group(rows: pa.Table, threshold: float) -> pa.Table:
    """Links between queries and members of other components.

    A pair that shares several bands is compared in the first of them only. Overlaps
    of a query with all members come from one pass over the members' shingle places.
    """
    rows = rows.combine_chunks()
    node = rows.column("node").to_numpy()
    component = rows.column("component").to_numpy()
    query = rows.column("query").to_numpy(zero_copy_only=False)
    at, ask = np.flatnonzero(~query), np.flatnonzero(query)
    out: list[tuple[int, int, float]] = []
    if len(at) and len(ask):
        band = rows.column("band")[0].as_py()
        bags_of, bands_of = rows.column("shingles").chunk(0), rows.column("bands").chunk(0)
        shingles = [bags_of[i].values.to_numpy() for i in range(len(node))]
        bands = np.stack([bands_of[i].values.to_numpy() for i in range(len(node))])
        size = np.array([len(x) for x in shingles])
        value = np.concatenate([shingles[i] for i in at])
        owner = np.repeat(np.arange(len(at)), size[at])
        order = np.argsort(value, kind="stable")
        value, owner = value[order], owner[order]
        for i in ask:
            same_band = bands[at] == bands[i]
            fair = (component[at] != component[i]) & (same_band.argmax(axis=1) == band) & same_band[:, band]
            fair &= np.minimum(size[at], size[i]) >= threshold * np.maximum(size[at], size[i])
            if not fair.any():
                continue
            low, high = np.searchsorted(value, shingles[i], "left"), np.searchsorted(value, shingles[i], "right")
            many = high - low
            places = np.arange(many.sum()) + np.repeat(low - np.cumsum(many) + many, many)
            same = np.bincount(owner[places], minlength=len(at))
            similarity = same / np.maximum(1, size[at] + size[i] - same)
            for k in np.flatnonzero(fair & (similarity >= threshold)):
                a, b = int(node[i]), int(node[at[k]])
                out.append((min(a, b), max(a, b), float(similarity[k])))
    a, b, c = zip(*out, strict=True) if out else ((), (), ())
    return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "similarity": pa.array(c, pa.float64())})


class NearDuplicates:
    """The stages of the search over docs (doc_id, text); classes() has the result."""

    def __init__(self, docs: DataFrame, threshold: float = THRESHOLD):
        self.spark, self.threshold = docs.sparkSession, threshold
        self.docs = docs.select("doc_id", "text")

    def _nodes(self) -> None:
        signed = stored(self.docs.where("doc_id is not null").mapInArrow(_signed, "doc_id long, digest binary, size long, bands array<bigint>"), "signed")
        # one text for each doc_id, one node for each distinct text, named by its smallest doc_id; partial minima
        # before the shuffle (stored, so that the joins have exchanges of their own, which Spark may split where a text is hot)
        self.texts = stored(signed.groupBy("doc_id").agg(F.min("digest").alias("digest")), "texts")
        nodes = stored(self.texts.where("digest is not null").groupBy("digest").agg(F.min("doc_id").alias("node")), "nodes")
        self.members = stored(self.texts.join(nodes, "digest").select("doc_id", "node"), "members")
        named = nodes.select("node", F.col("digest").alias("of"))
        self.heads = stored(signed.where("size > 0").join(named, F.col("doc_id") == F.col("node")).where("digest = of").select("node", "digest", "size", "bands"), "heads")
        keyed = self.heads.select("node", "size", F.posexplode("bands").alias("band", "key"))
        groups = stored(keyed.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"), "keys")
        self.grouped = stored(keyed.join(groups, "key"), "groups")  # members of groups of two and more

    def _stars(self) -> DataFrame:
        """Candidate pairs (a < b) of each group's pivot with its members."""
        met = self.grouped.groupBy("node").agg(F.sum("n").alias("met"))
        wide = stored(self.grouped.select("key", "node", "size").join(met, "node"), "met")
        top = F.max(F.struct("met", (-F.col("node")).alias("back"), "size")).alias("top")
        pivot = stored(wide.groupBy("key").agg(top).select("key", (-F.col("top.back")).alias("first"), F.col("top.size").alias("first_size")), "pivots")
        pairs = wide.join(pivot, "key").where("node <> first").where(self._fits("size", "first_size"))
        return pairs.select(F.least("first", "node").alias("a"), F.greatest("first", "node").alias("b")).distinct()

    def _bags(self) -> None:
        wanted = stored(self.heads.select("node", "digest").join(self.grouped.select("node").distinct(), "node", "left_semi"), "wanted")
        n = wanted.count()
        texts = self.docs.where("doc_id is not null and text is not null").withColumnRenamed("doc_id", "node").join(_bounded(wanted, n), "node").select("node", "digest", "text")
        self.bags = stored(texts.mapInArrow(_shingle_lists, "node long, shingles array<bigint>"), "bags")

    def _verified(self, pairs: DataFrame, name: str) -> DataFrame:
        """Links (a, b, similarity) among candidate pairs (a < b, distinct)."""
        left = self.bags.select(F.col("node").alias("a"), F.col("shingles").alias("left"))
        right = self.bags.select(F.col("node").alias("b"), F.col("shingles").alias("right"))
        threshold = self.threshold
        both = pairs.join(left, "a").join(right, "b").select("a", "b", "left", "right")
        return stored(both.mapInArrow(lambda batches: _overlaps(batches, threshold), "a long, b long, similarity double"), name)

    def _fits(self, a: str, b: str):
        """Bags whose sizes differ too much can't reach the threshold."""
        return F.least(a, b) >= F.greatest(a, b) * self.threshold

    def _with_least(self, both: DataFrame) -> DataFrame:
        """(u, v, m) for edges in both directions, m the smallest neighbour of u.

        Nodes of HOT_NODE edges and more are dealt over several tasks; there are at
        most edges / HOT_NODE of them, which is what is broadcast.
        """
        least = stored(both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")), "least")
        hot = least.where(F.col("n") >= HOT_NODE).select("u", F.ceil(F.col("n") / F.lit(HOT_NODE)).cast("int").alias("parts"))
        dealt = both.join(_bounded(hot, hot.count()), "u", "left").withColumn("part", F.pmod(F.xxhash64("v"), F.coalesce("parts", F.lit(1))).cast("int")).drop("parts")
        parts = F.ceil(F.col("n") / F.lit(HOT_NODE)).cast("int")
        return dealt.join(least.select("u", "m", F.explode(F.sequence(F.lit(0), parts - 1)).alias("part")), ["u", "part"]).select("u", "v", "m")

    def components(self, links: DataFrame) -> DataFrame:
        """(node, component) of linked nodes: the smallest node of each component.

        Each round links every node to the smallest neighbour of its neighbourhood
        (large and small stars in turn); the edges shrink to stars in a number of
        rounds that grows with the logarithm of the longest path.
        """
        edges = stored(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "edges")
        before = None
        while True:
            both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
            large = self._with_least(both).where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v")).where("u <> v").distinct()
            large = stored(large, "large")
            small = self._with_least(large).select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
            edges = stored(small, "edges")
            now = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s")).first()
            if before == now:
                return edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
            before = now

    def _rest(self, links: DataFrame) -> DataFrame:
        """Links between components that still share a group.

        In each group of several components, the members outside the largest one are
        a query set against all members, both dealt into chunks of CHUNK shingles.
        """
        found = self.components(links)
        rows = self.grouped.select("key", "band", "node", "size").join(found, "node", "left").withColumn("component", F.coalesce("component", "node"))
        sums = stored(rows.groupBy("key", "component").agg(F.count("*").alias("n"), F.sum("size").alias("size")), "sums")
        groups = sums.groupBy("key").agg(F.max(F.struct("n", "component", "size")).alias("top"), F.count("*").alias("parts"), F.sum("size").alias("total")).where("parts > 1")
        chunks = lambda c: F.ceil(c / F.lit(CHUNK)).cast("int")
        groups = groups.select("key", F.col("top.component").alias("largest"), chunks(F.col("total")).alias("m_chunks"), chunks(F.col("total") - F.col("top.size")).alias("q_chunks"))
        rows = rows.join(groups, "key")
        deal = lambda seed, n: F.pmod(F.xxhash64(F.lit(seed), "node"), n).cast("int")
        upto = lambda n: F.explode(F.sequence(F.lit(0), n - 1))
        columns = ["key", "band", "node", "component"]
        members = rows.select(*columns, F.lit(False).alias("query"), deal(1, F.col("m_chunks")).alias("m"), upto(F.col("q_chunks")).alias("q"))
        queries = rows.where("component <> largest").select(*columns, F.lit(True).alias("query"), upto(F.col("m_chunks")).alias("m"), deal(2, F.col("q_chunks")).alias("q"))
        threshold = self.threshold
        bands = self.heads.select("node", "bands")
        with_bags = members.unionByName(queries).join(self.bags, "node").join(bands, "node").select(*columns, "query", "m", "q", "bands", "shingles")
        return stored(with_bags.groupBy("key", "m", "q").applyInArrow(lambda t: _rest_of_group(t, threshold), "a long, b long, similarity double"), "rest")

    def links(self) -> DataFrame:
        """Verified links (a, b, similarity) that connect all near-duplicate nodes."""
        self._nodes()
        self._bags()
        links = self._verified(self._stars(), "links")
        return links.unionByName(self._rest(links))

    def classes(self) -> DataFrame:
        """doc_id, class_id (smallest doc_id of the class), is_kept: one row for each doc_id, and each row without one."""
        found = self.components(self.links())
        of = self.members.join(found, "node", "left").select("doc_id", F.coalesce("component", "node").alias("class_id"))
        alone = self.texts.where("digest is null").select("doc_id", F.col("doc_id").alias("class_id"))
        unnamed = self.docs.where("doc_id is null").select("doc_id", F.col("doc_id").alias("class_id"))
        return of.unionByName(alone).unionByName(unnamed).select("doc_id", "class_id", F.coalesce(F.col("doc_id") == F.col("class_id"), F.lit(True)).alias("is_kept"))


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    return NearDuplicates(docs, threshold).classes()


def keep_one_of_each_class(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Rows of docs, all columns, without those that repeat another: one row of each class stays.

    Rows of one doc_id are one document, of which one row stays; rows without a
    doc_id or text all stay.
    """
    classes = stored(near_duplicates(docs.where("doc_id is not null"), threshold), "classes")
    gone = classes.where("not is_kept").select("doc_id")
    kept = docs.join(_bounded(gone, gone.count()), "doc_id", "left_anti").select(*docs.columns)
    repeated = docs.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").select("doc_id")
    n = repeated.count()
    if not n:
        return kept
    several = _bounded(repeated, n)
    first = Window.partitionBy("doc_id").orderBy(F.xxhash64("text"))
    one = kept.join(several, "doc_id", "left_semi").select(*docs.columns).withColumn("_place", F.row_number().over(first)).where("_place = 1").drop("_place")
    return kept.join(several, "doc_id", "left_anti").select(*docs.columns).unionByName(one)
