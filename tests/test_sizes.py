"""Queries on larger or odder tables than the given ones: what failed there before."""

from __future__ import annotations

import numpy as np
import pytest

from tallgram.operators import accuracy, gram, sampling, similarity, spectral, tiles
from tallgram.operators.norms import column_norms
from tallgram.queries import all_queries

QUERIES, ORACLES = all_queries()


def test_power_sums_keep_the_sign_of_negative_eigenvalues(spark):
    upper = spark.createDataFrame([(0, 0, 1.0), (1, 1, 1.0), (0, 1, 3.0)], "i int, j int, dot double")  # eigenvalues 4 and -2
    assert tuple(spectral.power_sums(upper).first()) == (2.0, 20.0)
    assert tuple(spectral.power_sums(upper.where("false")).first()) == (0.0, 0.0)


def test_planned_spectrum_decomposes_nothing(spark, monkeypatch):
    monkeypatch.setattr(spectral, "DENSE_COLUMNS", 1)
    assert QUERIES["planned_spectrum_w4b"](spark, "/root/testdata/sf0.001").first()["method"] == "pair"


@pytest.mark.parametrize(("local_bytes", "block_columns", "parts"), [(1 << 20, 10, 1), (0, 10, 1), (0, 60, 1), (0, 20, 5), (0, 10, 5), (1 << 20, 35, 2)])
def test_sparse_norms_are_those_of_dense_matrices(spark, monkeypatch, local_bytes, block_columns, parts):
    rng, n = np.random.default_rng(3), 60
    part = np.minimum(np.arange(n) * parts // 40, parts - 1)  # the last part is larger than the others
    i, j = np.nonzero(np.triu(rng.random((n, n)) < 0.3) & (part[:, None] == part))
    monkeypatch.setattr(spectral, "BLOCK_COLUMNS", block_columns)
    a, b = rng.standard_normal((2, len(i)))
    both = spark.createDataFrame([(int(x), int(y), float(p), float(q)) for x, y, p, q in zip(i, j, a, b, strict=True)], "i int, j int, a double, b double")
    monkeypatch.setattr(spectral, "LOCAL_BYTES", local_bytes)
    want = [spectral.spectral_norm(spectral.dense(both, n, c)) for c in ("a", "b")]
    assert spectral.sparse_norms(both, n, ["a", "b"]) == pytest.approx(want, rel=1e-9)
    assert spectral.sparse_norms(both.where("false"), n, ["a", "b"]) == [0.0, 0.0]


def test_success_rate_beyond_dense_columns(spark, monkeypatch):
    small = "/root/testdata/sf0.001"
    want = QUERIES["success_rate_w4b"](spark, small).first()
    monkeypatch.setattr(accuracy, "DENSE_COLUMNS", 1)
    monkeypatch.setattr(spectral, "BLOCK_COLUMNS", 5)
    monkeypatch.setattr(spectral, "DENSE_COLUMNS", 1)
    got = QUERIES["success_rate_w4b"](spark, small).first()
    assert got[:2] == want[:2] and got[2:] == pytest.approx(want[2:], rel=1e-9)


def test_assembled_rows_are_those_of_the_batch_and_need_no_python_state(spark):
    from pyspark.sql import functions as F

    from tallgram.sources.tables import load_table
    from tallgram.streaming import events as E

    small = "/root/testdata/sf0.001"
    end = load_table(spark, small, "events").agg(F.max("ts")).first()[0]
    over = F.expr("cast(date_trunc('day', ts) as timestamp_ntz) + interval 1 day") <= F.lit(end) - F.expr("interval 1 hour")
    by_day = load_table(spark, small, "events").where(over).groupBy(F.expr("shiftleft(user_id, 20) + unix_date(to_date(ts))").alias("row_id"))
    want = by_day.agg(F.count_distinct(F.get_json_object("props", "$.k").cast("int")).alias("n"))
    assert sorted(QUERIES["stream_assembled_rows"](spark, small).collect()) == sorted(want.collect())
    plan = E.assemble_rows(E.watermarked(E.stream_events(spark, f"{small}/events.parquet*")))._jdf.queryExecution().analyzed().toString()
    assert "Python" not in plan and "Pandas" not in plan


@pytest.mark.parametrize("name", ["block_source", "lower_bound_blocks"])
def test_blocks_come_from_the_customers(spark, tmp_path, name):
    """Keys with gaps, a repeat and a null, in a folder of several files."""
    import duckdb
    from compare import differences, rows_of

    from tallgram.sources.tables import SCHEMAS

    keys = [*range(25), 41, 59, 59, None]
    rows = spark.createDataFrame([(k, "x", 1, 0.5, "y") for k in keys], SCHEMAS["customer"])
    rows.repartition(3).write.parquet(str(tmp_path / "customer.parquet"))
    for path in (tmp_path / "customer.parquet").glob("[._]*"):
        path.unlink()
    got = QUERIES[name](spark, str(tmp_path))
    c = duckdb.connect()
    c.execute(f"create view customer as select * from '{tmp_path}/customer.parquet/*.parquet'")
    rel = c.execute(ORACLES[name])
    assert rows_of(got.columns, got.collect()) == rows_of([x[0] for x in rel.description], rel.fetchall())
    assert differences(spark, QUERIES[name], ORACLES[name], "/root/testdata/sf0.001") == ""


def test_saved_pairs_leave_one_file_a_folder(spark, tmp_path):
    from tallgram.sources.files import load_pairs, save_pairs

    pairs = spark.range(400).selectExpr("cast(id % 20 as int) as i", "cast(id as int) + 20 as j", "0.5 as cos").repartition(8)
    save_pairs(pairs, str(tmp_path / "pairs"), 5)
    assert [len(list(p.glob("*.parquet"))) for p in (tmp_path / "pairs").glob("i_block=*")] == [1] * 4
    assert load_pairs(spark, str(tmp_path / "pairs"), 3, 7, 5).count() == 100


def test_wanted_pairs_are_looked_up_and_made_once(spark):
    rows = [(r, [(c, 1.0) for c in range(40) if (r * 7 + c) % 3]) for r in range(30)]
    m = spark.createDataFrame(rows, "row_id long, entries array<struct<col:int,val:double>>")
    made = spark.sparkContext.accumulator(0)

    def counted(batches):
        for batch in batches:
            made.add(batch.num_rows)
            yield batch

    wanted = spark.createDataFrame([(i, j) for i in range(5) for j in range(5, 40)], "i int, j int").mapInArrow(counted, "i int, j int")
    found = similarity.exact_of(m, wanted)
    assert {(r["i"], r["j"]): r["dot"] for r in found.collect()} == {(i, j): float(n) for i in range(5) for j in range(5, 40) if (n := sum(c[0] == i for _, e in rows for c in e if (j, 1.0) in e))}
    assert made.value == 175
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "array_contains" not in plan


def _plain(df):
    return sorted(tuple(round(v, 9) if isinstance(v, float) else v for v in r) for r in df.collect())


@pytest.fixture(scope="module")
def odd_rows(spark):
    """Row numbers of one to ten digits and a negative one, columns of one to three digits, values that cancel out."""
    rng = np.random.default_rng(5)
    rows = []
    for r, row_id in enumerate([-3, 7, 10, 4321, 99999, 10**9 + 7, *range(200, 240)]):
        cols = np.flatnonzero(rng.random(130) < 0.3)
        rows.append((row_id, [(int(c), float(rng.integers(1, 4) * (-1) ** (r + c % 2 * (r // 2)))) for c in cols]))
    return spark.createDataFrame([*rows, (5, [])], "row_id long, entries array<struct<col:int,val:double>>").persist()


BOUNDS = [[0], [0, 9, 64, 120], [0, 40, 200]]


def _exchanges(df) -> int:
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange ")


@pytest.mark.parametrize("bounds", BOUNDS)
def test_best_partners_by_tiles(spark, odd_rows, monkeypatch, bounds):
    monkeypatch.setattr(tiles, "CELLS", 500)
    cosines = gram.exact_cosines(odd_rows).selectExpr("i", "j", "round(cos, 2) as cos")  # two digits: many ties
    assert _plain(tiles.top_k_similar(odd_rows, 3, 2, bounds)) == _plain(similarity.top_k_similar(cosines, 3))
    assert tiles.top_k_similar(odd_rows.where("false"), 3, 2).count() == 0


def test_similar_users_leave_few_rows_for_an_exchange(spark):
    """The best of a column in each tile at most, not all pairs: these were on disk before."""
    from tallgram.operators.cost import shuffled

    top = QUERIES["topk_similar_w1"](spark, "/root/testdata/sf0.01")
    assert shuffled(top)[0] <= 2 * 3 * 150


def test_blocks_have_about_equal_entries(spark):
    m = spark.createDataFrame([(r, [(c, 1.0) for c in range(r % 7, 1000, 7)]) for r in range(50)], "row_id long, entries array<struct<col:int,val:double>>")
    assert tiles.blocks(m) == [0]
    bounds = tiles.blocks(m, 4)
    assert len(bounds) == 4 and all(190 <= b - a <= 330 for a, b in zip(bounds, [*bounds[1:], 1000], strict=True))


@pytest.mark.parametrize("bounds", BOUNDS)
def test_exact_cosines_by_tiles(spark, odd_rows, monkeypatch, bounds):
    monkeypatch.setattr(tiles, "CELLS", 500)
    monkeypatch.setattr(tiles, "CHUNK", 200)
    got = tiles.exact_cosines(odd_rows, bounds=bounds)
    assert _plain(got) == _plain(gram.exact_cosines(odd_rows))
    assert got.where("dot = 0").count() > 0  # pairs whose products cancel out are kept


def test_cosines_of_users_exchange_no_pairs(spark):
    """Records of all exchanges: entries on their way to rows and tiles; before, 7,788 pairs and more."""
    from tallgram.operators.cost import shuffled

    found = QUERIES["exact_cosines_w1"](spark, "/root/testdata/sf0.01")
    assert shuffled(found)[0] < 100 and found.count() == 7788


def test_rounding_is_that_of_sql():
    import duckdb

    values = [0.0078125, -0.0234375, 0.0000005, 0.1234565, 2 / 3, 1e-9, 12345678.0000005, 1.0, 0.0]
    want = duckdb.execute("select round(unnest(?::double[]), 6)", [values]).fetchall()
    assert tiles.half_up(np.array(values), 6).tolist() == [x for (x,) in want]
    assert tiles.half_up(np.array(values), None).tolist() == values


@pytest.mark.parametrize("bounds", BOUNDS)
@pytest.mark.parametrize("gamma", [3.0, 60.0, np.inf])
def test_samples_by_tiles_are_those_of_the_draws(spark, odd_rows, monkeypatch, bounds, gamma):
    """Rows and columns of different lengths in digits, chunks that end inside a row."""
    monkeypatch.setattr(tiles, "CELLS", 500)
    monkeypatch.setattr(tiles, "CHUNK", 300)
    monkeypatch.setattr(tiles, "DRAWS", 70)
    assert _plain(tiles.sampled_cosines(odd_rows, gamma, 12345, bounds=bounds)) == _plain(sampling.sampled_cosines(odd_rows, gamma, 12345, draw="md5"))


def test_samples_of_users_exchange_no_pairs(spark):
    """Records of all exchanges; before, 2,241 pairs and more."""
    from tallgram.operators.cost import shuffled

    found = QUERIES["sampled_w1"](spark, "/root/testdata/sf0.01")
    assert shuffled(found)[0] < 100 and found.count() == 2241


def test_first_words_of_digests():
    import hashlib

    texts = [f"7|{r}|{i}|4" for r in (0, -5, 10**17) for i in (3, 44)]
    for text in texts:
        block = (text.encode() + b"\x80").ljust(56, b"\0") + (8 * len(text)).to_bytes(8, "little")
        words = [np.array([x], np.uint32) for x in np.frombuffer(block, "<u4")]
        assert int(tiles._first_words(words, 1)[0]) == int(hashlib.md5(text.encode()).hexdigest()[:8], 16)


def test_draws_that_the_first_word_leaves_open(spark):
    """A bound just at the draw: the rest of the digits decides."""
    import hashlib

    ones = lambda cols: tiles._Side(0, False, [np.array([len(cols)], np.uint32).tobytes()], [np.array(cols, np.uint32).tobytes()], [b""])
    side = ones([2, 5])
    draws = tiles._Draws(tiles._Tile(np.array([77]), side, side), 7)
    draw = int(hashlib.md5(b"7|77|2|5").hexdigest()[:13], 16) / float(1 << 52)
    under = [bool(draws.under(np.array([0]), np.array([1]), np.array([p]))[0]) for p in (draw - 2.0**-52, draw, draw + 2.0**-52)]
    assert under == [False, False, True]


@pytest.mark.parametrize("bounds", BOUNDS)
def test_cells_by_tiles_are_those_of_the_grid(spark, odd_rows, monkeypatch, bounds):
    monkeypatch.setattr(tiles, "CELLS", 500)
    monkeypatch.setattr(tiles, "CHUNK", 300)
    norms, seeds = column_norms(odd_rows), [3, 14]
    grid = accuracy.grid(sampling.repeated_estimates(odd_rows, "pair", 9.0, seeds, norms, "md5"), gram.exact_cosines(odd_rows, norms), seeds)
    got = tiles.cells(odd_rows, 9.0, seeds, 0.1, bounds)
    assert got.count() > 0 and _plain(got) == _plain(grid.where("exact >= 0.1"))


def test_tails_of_words_exchange_no_pairs(spark):
    """Records of all exchanges; before, all pairs under each of six seeds."""
    from tallgram.operators.cost import shuffled

    assert shuffled(QUERIES["tails_over_seeds_w2b"](spark, "/root/testdata/sf0.01"), last=False)[0] < 100_000


@pytest.mark.parametrize(("in_tasks", "sums_bytes"), [(True, 0), (False, 0), (False, 1 << 20)])
def test_difference_norms_are_those_of_dense_matrices(spark, odd_rows, monkeypatch, in_tasks, sums_bytes):
    """Rows of very different lengths, negative row numbers and values, duplicates to be summed, records that hold a part of a row's matrix."""
    from tallgram.operators import differences
    from tallgram.operators.matrix import to_triplets

    for name, value in (("TASK_COLUMNS", 1000 if in_tasks else 1), ("CHUNK", 300), ("CELLS", 700), ("SUMS_BYTES", sums_bytes)):
        monkeypatch.setattr(differences, name, value)
    m = odd_rows.selectExpr("row_id", "filter(entries, e -> e.col < 30) as entries").persist()
    norms, n, seeds = column_norms(m).persist(), 30, [3, 14]
    runs = [("pair", 9.0), ("staged", 9.0), ("thinned", 9.0), ("pair", 1e9)]
    upper = gram.exact_gram(m).select("i", "j", "dot").unionByName(norms.selectExpr("col as i", "col as j", "sumsq as dot")).persist()
    t = to_triplets(m)
    halves = t.unionByName(t.where("col % 3 = 0")).withColumn("val", t["val"] / (1 + (t["col"] % 3 == 0).cast("int")))
    base, found = differences.sampled_difference_norms(halves.unionByName(t.selectExpr("row_id", "col + 1 as col", "0.0 as val").where("col < 30")), n, runs, seeds)
    assert base == pytest.approx(spectral.spectral_norm(spectral.dense(upper, n)), rel=1e-9)
    for (method, gamma), got in zip(runs, found, strict=True):
        want = accuracy.spectral_errors(sampling.repeated_estimates(m, method, gamma, seeds, norms), norms, upper, n, seeds, base)
        assert [x / base for x in got] == pytest.approx(want, rel=1e-9, abs=1e-12)
    assert differences.sampled_difference_norms(t.where("false"), n, runs[:1], seeds) == (0.0, [[0.0, 0.0]])


@pytest.mark.parametrize("name", ["method_ablation_w4b", "success_rate_w4b"])
def test_errors_of_many_suppliers_exchange_no_pairs(spark, monkeypatch, name):
    """Neither estimates nor exact products become rows of pairs; the results are the same."""
    small = "/root/testdata/sf0.001"
    want = QUERIES[name](spark, small).collect()
    monkeypatch.setattr(accuracy, "DENSE_COLUMNS", 1)
    for module, made in ((sampling, "repeated_estimates"), (gram, "exact_gram")):
        monkeypatch.setattr(module, made, None)
    got = QUERIES[name](spark, small).collect()
    assert [r[:2] for r in got] == [r[:2] for r in want] and [x for r in got for x in r[2:]] == pytest.approx([x for r in want for x in r[2:]], rel=1e-9)


def test_errors_of_many_words_exchange_no_pairs(spark, monkeypatch):
    """Steps over rows with draws as bits; the same results."""
    from tallgram.operators import differences

    small = "/root/testdata/sf0.001"
    want = QUERIES["success_rate_w2b"](spark, small).collect()
    monkeypatch.setattr(accuracy, "DENSE_COLUMNS", 0)
    monkeypatch.setattr(differences, "TASK_COLUMNS", 0)
    for module, made in ((sampling, "repeated_estimates"), (gram, "exact_gram")):
        monkeypatch.setattr(module, made, None)
    got = QUERIES["success_rate_w2b"](spark, small).collect()
    assert [r[:2] for r in got] == [r[:2] for r in want] and [x for r in got for x in r[2:]] == pytest.approx([x for r in want for x in r[2:]], rel=1e-9)
