"""Queries of the surrounding operators: scans, joins, aggregations, windows, sets, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tallgram.functions import udfs
from tallgram.operators import gram, matrix, sampling, similarity
from tallgram.operators.norms import column_norms
from tallgram.queries import add, query, sql
from tallgram.sources import workloads
from tallgram.sources.tables import load_table, register_views

T = load_table


def _round(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def _cosines(s, d, w="w2b") -> DataFrame:
    return gram.exact_cosines(workloads.matrix(s, d, w))


_COS_W2B = f"{sql.matrix('w2b')}, {sql.PAIRS}, e as (select i, j, sum(x * y) / max(ni * nj) as cos from q group by i, j)"
_COS_W4 = f"{sql.matrix('w4')}, {sql.PAIRS}, e as (select i, j, sum(x * y) / max(ni * nj) as cos from q group by i, j)"

# --- projections and predicates ---


@query("filter_lines", "select l_orderkey, l_linenumber, l_quantity * 2 as twice, case when l_discount > 0.05 then 'high' when l_discount > 0 then 'low' else 'none' end as band from lineitem where l_quantity between 10 and 20 and l_returnflag in ('A','R') and l_linestatus like 'F%'")
def filter_lines(s, d):
    lines = T(s, d, "lineitem").where(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & F.col("l_linestatus").like("F%"))
    band = F.when(F.col("l_discount") > 0.05, "high").when(F.col("l_discount") > 0, "low").otherwise("none")
    return lines.select("l_orderkey", "l_linenumber", (F.col("l_quantity") * 2).alias("twice"), band.alias("band"))


@query("filter_regex", "select p_partkey, upper(p_brand) as brand from part where regexp_matches(p_brand, '[13]$') and p_size <> 7")
def filter_regex(s, d):
    return T(s, d, "part").where(F.col("p_brand").rlike("[13]$") & (F.col("p_size") != 7)).select("p_partkey", F.upper("p_brand").alias("brand"))


@query("filter_null_safe", "select d.doc_id, l.toxic from documents d left join labels l using (doc_id) where l.toxic is not distinct from null or l.toxic = 1")
def filter_null_safe(s, d):
    both = T(s, d, "documents").select("doc_id").join(T(s, d, "labels").select("doc_id", "toxic"), "doc_id", "left")
    return both.where(F.col("toxic").eqNullSafe(F.lit(None)) | (F.col("toxic") == 1))


@query("drop_zero_discounts", "select l_orderkey as row_id, l_linenumber as col, l_discount as val from lineitem where l_discount <> 0")
def drop_zero_discounts(s, d):
    lines = T(s, d, "lineitem").select(F.col("l_orderkey").alias("row_id"), F.col("l_linenumber").alias("col"), F.col("l_discount").alias("val"))
    return matrix.drop_invalid(lines)


@query("distinct_entries_w4", f"select row_id, label from ({sql.LABELLED['w4']})")
def distinct_entries_w4(s, d):
    return workloads.brands_by_order(s, d).select("row_id", "label")


@query("min_support_w2", f"select label, count(*) as n from ({sql.LABELLED['w2']}) group by label")
def min_support_w2(s, d):
    return workloads.words_by_turn(s, d, 5).groupBy("label").agg(F.count("*").alias("n"))


@query("cap_rows_w2b", f"with {sql.matrix('w2b')}, r as (select row_id, count(*) as k from m group by row_id) select row_id, k as n from r where k <= 12")
def cap_rows_w2b(s, d):
    return matrix.cap_rows(workloads.matrix(s, d, "w2b"), 12).select("row_id", F.size("entries").cast("long").alias("n"))


@query("keep_heavy_entries_w4c", f"with {sql.matrix('w4c')} select row_id, count(*) filter (where val >= 40) as n from m group by row_id")
def keep_heavy_entries_w4c(s, d):
    return matrix.keep_entries(workloads.matrix(s, d, "w4c"), lambda e: e["val"] >= 40).select("row_id", F.size("entries").cast("long").alias("n"))


@query("row_as_map_w4", f"with {sql.matrix('w4')} select row_id, count(*) as n, sum(col)::bigint as cols, sum(val) as total from m group by row_id")
def row_as_map_w4(s, d):
    m = matrix.row_as_map(workloads.matrix(s, d, "w4"))
    total = F.aggregate(F.map_values("row"), F.lit(0.0), lambda a, v: a + v)
    cols = F.aggregate(F.map_keys("row"), F.lit(0).cast("long"), lambda a, c: a + c)
    return m.select("row_id", F.size("row").cast("long").alias("n"), cols.alias("cols"), total.alias("total"))


# --- joins ---


@query("broadcast_label_w4", f"with {_COS_W4} select x.label as left_label, y.label as right_label, round(cos, 6) as cos from e join d x on x.col = e.i join d y on y.col = e.j")
def broadcast_label_w4(s, d):
    names = workloads.dictionary(s, d, "w4")
    side = lambda k, n: F.broadcast(names.select(F.col("col").alias(k), F.col("label").alias(n)))
    return _round(_cosines(s, d, "w4").join(side("i", "left_label"), "i").join(side("j", "right_label"), "j").select("left_label", "right_label", "cos"))


@query("semi_join_labelled", "select doc_id, lang from documents where doc_id in (select doc_id from labels where toxic = 1)")
def semi_join_labelled(s, d):
    return T(s, d, "documents").select("doc_id", "lang").join(T(s, d, "labels").where("toxic = 1").select("doc_id"), "doc_id", "left_semi")


@query("anti_join_unlabelled", "select doc_id, lang from documents where doc_id not in (select doc_id from labels)")
def anti_join_unlabelled(s, d):
    return T(s, d, "documents").select("doc_id", "lang").join(T(s, d, "labels").select("doc_id"), "doc_id", "left_anti")


_SAMPLE_W4B = f"s as (select i, j, sum(x * y) / least({sql.real(25.0)}, max(ni * nj)) as est from q where {sql.pair_kept(25.0, 7)} group by i, j)"


@query("full_outer_compare_w4b", f"with {sql.matrix('w4b')}, {sql.PAIRS}, e as (select i, j, sum(x * y) / max(ni * nj) as cos from q group by i, j), {_SAMPLE_W4B} select i, j, round(cos, 6) as exact, round(est, 6) as estimate, est is null as unseen from e full join s using (i, j)")
def full_outer_compare_w4b(s, d):
    m = workloads.matrix(s, d, "w4b")
    a = sampling.sampled_cosines(m, 25.0, 7, draw="md5").select("i", "j", F.col("cos").alias("estimate"))
    b = gram.exact_cosines(m).select("i", "j", F.col("cos").alias("exact"))
    return _round(b.join(a, ["i", "j"], "full").select("i", "j", "exact", "estimate", F.col("estimate").isNull().alias("unseen")))


@query("unseen_pairs_w4b", f"with {sql.matrix('w4b')}, {sql.PAIRS}, e as (select i, j from q group by i, j), {_SAMPLE_W4B} select i, j from e anti join s using (i, j)")
def unseen_pairs_w4b(s, d):
    m = workloads.matrix(s, d, "w4b")
    return gram.exact_gram(m).select("i", "j").join(sampling.sampled_cosines(m, 25.0, 7, draw="md5"), ["i", "j"], "left_anti")


@query("left_join_supplier_parts", "select s_suppkey, s_name, count(l_orderkey) as lines from supplier left join lineitem on s_suppkey = l_suppkey group by all")
def left_join_supplier_parts(s, d):
    lines = T(s, d, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("lines"))
    joined = T(s, d, "supplier").join(lines, F.col("s_suppkey") == F.col("l_suppkey"), "left")
    return joined.select("s_suppkey", "s_name", F.coalesce("lines", F.lit(0)).alias("lines"))


@query("right_join_regions", "select r_name, count(n_nationkey) as nations from nation right join region on n_regionkey = r_regionkey group by r_name")
def right_join_regions(s, d):
    return T(s, d, "nation").join(T(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"), "right").groupBy("r_name").agg(F.count("n_nationkey").alias("nations"))


@query("merge_join_orders", "select o_orderpriority, count(*) as lines, round(sum(l_extendedprice), 2) as price from lineitem join orders on l_orderkey = o_orderkey and l_shipdate > o_orderdate group by all")
def merge_join_orders(s, d):
    lines = T(s, d, "lineitem").select("l_orderkey", "l_shipdate", "l_extendedprice")
    both = lines.hint("merge").join(T(s, d, "orders"), (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") > F.col("o_orderdate")))
    return both.groupBy("o_orderpriority").agg(F.count("*").alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query("range_join_events", "select a.event_id, count(*) as near from events a join events b on a.user_id = b.user_id and b.ts between a.ts - interval 1 hour and a.ts + interval 1 hour and a.event_id <> b.event_id group by a.event_id")
def range_join_events(s, d):
    """Events of one user within an hour of each other: hour buckets make it an equality join."""
    e = T(s, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = 3_600_000_000
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("us").alias("at"), F.explode(F.expr(f"sequence(us div {hour} - 1, us div {hour} + 1)")).alias("bucket"))
    b = e.select(F.col("event_id").alias("b"), F.col("user_id").alias("u"), F.col("us").alias("to"), F.expr(f"us div {hour}").alias("k"))
    near = a.join(b, (F.col("user_id") == F.col("u")) & (F.col("bucket") == F.col("k"))).where((F.abs(F.col("to") - F.col("at")) <= hour) & (F.col("a") != F.col("b")))
    return near.groupBy(F.col("a").alias("event_id")).agg(F.count("*").alias("near"))


@query("asof_events", "select p.event_id, v.event_id as before from (select * from events where event_type = 'purchase') p asof join (select user_id, ts, max(event_id) as event_id from events where event_type = 'view' group by all) v on p.user_id = v.user_id and p.ts >= v.ts")
def asof_events(s, d):
    """The last view at or before each purchase of the user: one union and a running window, no pair is made."""
    e = T(s, d, "events").where(F.col("event_type").isin("purchase", "view")).select("event_id", "user_id", "ts", "event_type")
    order = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(order)
    return e.withColumn("before", last).where("event_type = 'purchase' and before is not null").select("event_id", "before")


@query("lateral_pairs_w4", sql.with_pairs("w4", "select i, j, count(*) as n from q group by i, j"))
def lateral_pairs_w4(s, d):
    udfs.register(s)
    workloads.matrix(s, d, "w4").createOrReplaceTempView("w4_rows")
    return s.sql("select i, j, count(*) as n from w4_rows, lateral emit_pairs(entries) group by i, j")


@query("norm_pairs_theta_w4", f"with {sql.matrix('w4')} select a.col as i, b.col as j from c a join c b on a.norm < b.norm and a.nnz * 1.05 >= b.nnz")
def norm_pairs_theta_w4(s, d):
    """A pure inequality join of column norms: as many rows as columns, broadcast."""
    c = column_norms(workloads.matrix(s, d, "w4"))
    a, b = c.select(F.col("col").alias("i"), F.col("norm").alias("x"), F.col("nnz").alias("n")), c.select(F.col("col").alias("j"), F.col("norm").alias("y"), F.col("nnz").alias("k"))
    return a.join(F.broadcast(b), (F.col("x") < F.col("y")) & (F.col("n") * 1.05 >= F.col("k"))).select("i", "j")


# --- aggregations ---


@query("aggregate_lines", "select l_returnflag, l_linestatus, count(*) as n, sum(l_quantity) as quantity, round(avg(l_extendedprice), 4) as price, min(l_shipdate) as first_day, max(l_shipdate) as last_day, round(var_samp(l_quantity), 4) as spread, round(stddev_pop(l_quantity), 4) as deviation from lineitem group by all")
def aggregate_lines(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.min("l_shipdate").alias("first_day"), F.max("l_shipdate").alias("last_day"), F.round(F.var_samp("l_quantity"), 4).alias("spread"), F.round(F.stddev_pop("l_quantity"), 4).alias("deviation"))


@query("distinct_counts", "select count(distinct l_orderkey) as orders, count(distinct l_suppkey) as suppliers from lineitem")
def distinct_counts(s, d):
    return T(s, d, "lineitem").agg(F.count_distinct("l_orderkey").alias("orders"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("approximate_counts")
def approximate_counts(s, d):
    return T(s, d, "lineitem").agg(F.approx_count_distinct("l_orderkey").alias("orders"), F.percentile_approx("l_extendedprice", 0.5).alias("median"))


@query("quantiles_w2b", f"with {sql.matrix('w2b')} select round(quantile_cont(norm, 0.5), 6) as half, round(quantile_cont(norm, 0.9), 6) as ninth from c")
def quantiles_w2b(s, d):
    c = column_norms(workloads.matrix(s, d, "w2b"))
    return c.agg(F.round(F.percentile("norm", 0.5), 6).alias("half"), F.round(F.percentile("norm", 0.9), 6).alias("ninth"))


@query("correlations", "select round(corr(l_quantity, l_extendedprice), 6) as r, round(covar_pop(l_quantity, l_extendedprice), 2) as c from lineitem")
def correlations(s, d):
    return T(s, d, "lineitem").agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.covar_pop("l_quantity", "l_extendedprice"), 2).alias("c"))


@query("collected_row_form_w4", f"with {sql.matrix('w4')} select row_id, array_to_string(list(col order by col), ',') as cols from m group by row_id")
def collected_row_form_w4(s, d):
    return workloads.matrix(s, d, "w4").select("row_id", F.array_join(F.transform("entries", lambda e: e["col"].cast("string")), ",").alias("cols"))


@query("best_partner_w2b", f"with {_COS_W2B}, b as (select i, j, round(cos, 9) as cos from e union all select j, i, round(cos, 9) from e) select i, j, cos from b qualify row_number() over (partition by i order by cos desc, j) = 1")
def best_partner_w2b(s, d):
    both = gram.mirror(_round(_cosines(s, d).select("i", "j", "cos"), 9))
    return both.groupBy("i").agg(F.max(F.struct("cos", (-F.col("j")).alias("back"))).alias("b")).select("i", (-F.col("b.back")).alias("j"), "b.cos")


@query("conditional_counts", "select event_type, count(*) filter (where value > 100) as big, sum(case when user_id % 2 = 0 then 1 else 0 end)::bigint as even from events group by event_type")
def conditional_counts(s, d):
    return T(s, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 100).alias("big"), F.sum(F.when(F.col("user_id") % 2 == 0, 1).otherwise(0)).alias("even"))


@query("grouping_sets_docs", "select lang, source, count(*) as n, grouping(lang)::int as all_langs from documents group by grouping sets ((lang, source), (lang), ())")
def grouping_sets_docs(s, d):
    register_views(s, d)
    return s.sql("select lang, source, count(*) as n, cast(grouping(lang) as int) as all_langs from documents group by grouping sets ((lang, source), (lang), ())")


@query("rollup_events", "select dayofmonth(ts)::int as day, event_type, count(*) as n, round(sum(value), 4) as total from events group by rollup (1, 2)")
def rollup_events(s, d):
    return T(s, d, "events").select(F.dayofmonth("ts").alias("day"), "event_type", "value").rollup("day", "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))


@query("cube_docs", "select lang, source, sum(n_chars)::bigint as chars from documents group by cube (lang, source)")
def cube_docs(s, d):
    return T(s, d, "documents").cube("lang", "source").agg(F.sum("n_chars").alias("chars"))


@query("pivot_events", "select user_id, count(*) filter (where event_type = 'view') as view, count(*) filter (where event_type = 'click') as click, count(*) filter (where event_type = 'purchase') as purchase from events group by user_id having count(*) filter (where event_type in ('view','click','purchase')) > 0")
def pivot_events(s, d):
    kinds = ["view", "click", "purchase"]
    return T(s, d, "events").where(F.col("event_type").isin(kinds)).groupBy("user_id").pivot("event_type", kinds).count().na.fill(0, kinds)


@query("unpivot_nation", "select c_nationkey, kind, v from (select c_nationkey, round(min(c_acctbal), 2) as least, round(max(c_acctbal), 2) as most from customer group by all) unpivot (v for kind in (least, most))")
def unpivot_nation(s, d):
    wide = T(s, d, "customer").groupBy("c_nationkey").agg(F.round(F.min("c_acctbal"), 2).alias("least"), F.round(F.max("c_acctbal"), 2).alias("most"))
    return wide.unpivot("c_nationkey", ["least", "most"], "kind", "v")


@query("having_busy_users", "select user_id, count(*) as n from events group by user_id having count(*) >= 70")
def having_busy_users(s, d):
    return T(s, d, "events").groupBy("user_id").agg(F.count("*").alias("n")).where("n >= 70")


@query("row_norms_w4c", f"with {sql.matrix('w4c')} select row_id, round(sqrt(sum(val * val)), 6) as norm from m group by row_id")
def row_norms_w4c(s, d):
    squares = F.aggregate("entries", F.lit(0.0), lambda a, e: a + e["val"] * e["val"])
    return workloads.matrix(s, d, "w4c").select("row_id", F.round(F.sqrt(squares), 6).alias("norm"))


# --- windows ---


@query("window_ranks_w2b", f"with {_COS_W2B}, b as (select i, j, round(cos, 6) as cos from e) select i, j, cos, row_number() over (partition by i order by cos desc, j) as rn, rank() over (partition by i order by cos desc) as rk, dense_rank() over (partition by i order by cos desc) as dr from b")
def window_ranks_w2b(s, d):
    by = Window.partitionBy("i").orderBy(F.desc("cos"))
    exact = Window.partitionBy("i").orderBy(F.desc("cos"), "j")
    return _round(_cosines(s, d).select("i", "j", "cos")).select("i", "j", "cos", F.row_number().over(exact).alias("rn"), F.rank().over(by).alias("rk"), F.dense_rank().over(by).alias("dr"))


@query("window_deciles_w2b", f"with {sql.matrix('w2b')} select col, ntile(10) over (order by norm, col) as decile, round(percent_rank() over (order by norm), 9) as pr, round(cume_dist() over (order by norm), 9) as cd from c")
def window_deciles_w2b(s, d):
    c = column_norms(workloads.matrix(s, d, "w2b"))
    by = Window.orderBy("norm")
    return c.select("col", F.ntile(10).over(Window.orderBy("norm", "col")).alias("decile"), F.round(F.percent_rank().over(by), 9).alias("pr"), F.round(F.cume_dist().over(by), 9).alias("cd"))


_DAYS = "e as (select dayofmonth(ts)::int as day, count(*) as n from events group by 1)"


def _days(s, d) -> DataFrame:
    return T(s, d, "events").groupBy(F.dayofmonth("ts").alias("day")).agg(F.count("*").alias("n"))


@query("window_lag_days", f"with {_DAYS} select day, n, lag(n) over (order by day) as before, lead(n, 2) over (order by day) as later from e")
def window_lag_days(s, d):
    by = Window.orderBy("day")
    return _days(s, d).select("day", "n", F.lag("n").over(by).alias("before"), F.lead("n", 2).over(by).alias("later"))


@query("window_edges_days", f"with {_DAYS} select day, n, first_value(n) over w as a, last_value(n) over w as b, nth_value(n, 2) over w as c from e window w as (order by day rows between unbounded preceding and unbounded following)")
def window_edges_days(s, d):
    w = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _days(s, d).select("day", "n", F.first("n").over(w).alias("a"), F.last("n").over(w).alias("b"), F.nth_value("n", 2).over(w).alias("c"))


@query("window_running_days", f"with {_DAYS} select day, sum(n) over (order by day)::bigint as upto, round(avg(n) over (order by day rows between 6 preceding and current row), 6) as week from e")
def window_running_days(s, d):
    by = Window.orderBy("day")
    return _days(s, d).select("day", F.sum("n").over(by.rowsBetween(Window.unboundedPreceding, 0)).alias("upto"), F.round(F.avg("n").over(by.rowsBetween(-6, 0)), 6).alias("week"))


@query("window_range_orders", "select o_orderkey, count(*) over (partition by o_custkey order by o_orderdate::date - date '1970-01-01' range between 30 preceding and current row) as recent from orders")
def window_range_orders(s, d):
    day = F.datediff(F.to_date("o_orderdate"), F.lit("1970-01-01").cast("date"))
    by = Window.partitionBy("o_custkey").orderBy(day).rangeBetween(-30, 0)
    return T(s, d, "orders").select("o_orderkey", F.count("*").over(by).alias("recent"))


@query("window_share_w4", sql.with_pairs("w4", ", g as (select i, j, count(*) as n from q group by i, j) select i, j, round(n / sum(n) over (), 9) as share from g"))
def window_share_w4(s, d):
    g = gram.exact_gram(workloads.matrix(s, d, "w4"))
    return g.select("i", "j", F.round(F.col("n_terms") / F.sum("n_terms").over(Window.partitionBy()), 9).alias("share"))


# --- sorts, limits, sets ---


@query("top_pairs_w2b", f"with {_COS_W2B} select i, j, round(cos, 6) as cos from e order by round(cos, 6) desc, i, j limit 25")
def top_pairs_w2b(s, d):
    return _round(_cosines(s, d).select("i", "j", "cos")).orderBy(F.desc("cos"), "i", "j").limit(25)


@query("paged_orders", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20 offset 40")
def paged_orders(s, d):
    return T(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(40).limit(20)


@query("sorted_norms_w4", f"with {sql.matrix('w4')} select col, nnz from c order by nnz desc, col")
def sorted_norms_w4(s, d):
    return column_norms(workloads.matrix(s, d, "w4")).select("col", "nnz").orderBy(F.desc("nnz"), "col")


def _two_samples(s, d) -> tuple[DataFrame, DataFrame]:
    m = workloads.matrix(s, d, "w4b")
    norms = column_norms(m)
    return tuple(sampling.pair_emissions(m, 25.0, seed, norms, "md5").select("i", "j") for seed in (7, 8))


_TWO = f"with {sql.matrix('w4b')}, {sql.PAIRS}, a as (select i, j from q where {sql.pair_kept(25.0, 7)}), b as (select i, j from q where {sql.pair_kept(25.0, 8)})"
add("union_seeds_w4b", lambda s, d: (lambda a, b: a.union(b).distinct())(*_two_samples(s, d)), f"{_TWO} select * from a union select * from b")
add("union_all_seeds_w4b", lambda s, d: (lambda a, b: a.unionByName(b))(*_two_samples(s, d)), f"{_TWO} select * from a union all select * from b")
add("intersect_seeds_w4b", lambda s, d: (lambda a, b: a.intersect(b))(*_two_samples(s, d)), f"{_TWO} select * from a intersect select * from b")
add("intersect_all_seeds_w4b", lambda s, d: (lambda a, b: a.intersectAll(b))(*_two_samples(s, d)), f"{_TWO} select * from a intersect all select * from b")
add("except_seeds_w4b", lambda s, d: (lambda a, b: a.subtract(b))(*_two_samples(s, d)), f"{_TWO} select * from a except select * from b")
add("except_all_seeds_w4b", lambda s, d: (lambda a, b: a.exceptAll(b))(*_two_samples(s, d)), f"{_TWO} select * from a except all select * from b")

# --- functions ---


@query("json_keys_events", "select event_id, cast(json_extract_string(props, '$.k') as integer) as k from events")
def json_keys_events(s, d):
    return T(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("string_functions", "select p_partkey, length(p_name) as n, trim(lower(p_name)) as name, substring(p_brand, 1, 5) as head, replace(p_type, ' ', '_') as kind, split_part(p_brand, '#', 2) as code from part")
def string_functions(s, d):
    return T(s, d, "part").select("p_partkey", F.length("p_name").cast("long").alias("n"), F.trim(F.lower("p_name")).alias("name"), F.substring("p_brand", 1, 5).alias("head"), F.regexp_replace("p_type", " ", "_").alias("kind"), F.split_part("p_brand", F.lit("#"), F.lit(2)).alias("code"))


@query("date_functions", "select o_orderkey, year(o_orderdate)::int as y, date_trunc('month', o_orderdate)::date as month, (o_orderdate::date - date '1992-01-01')::int as days from orders")
def date_functions(s, d):
    return T(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.to_date(F.date_trunc("month", "o_orderdate")).alias("month"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"))


@query("word_counts_documents", r"select label, count(*) as n from (select unnest(regexp_extract_all(lower(text), '\p{L}+')) as label from documents) group by label having count(*) >= 200")
def word_counts_documents(s, d):
    words = F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), 1)).alias("label")
    return T(s, d, "documents").select(words).groupBy("label").agg(F.count("*").alias("n")).where("n >= 200")


@query("array_functions", "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x)), 5) as squares, len(list_filter(embedding, lambda x: x > 0))::int as positive, round(list_max(embedding)::double, 6) as most from embeddings")
def array_functions(s, d):
    e = T(s, d, "embeddings")
    squares = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x)
    return e.select("vec_id", F.round(squares, 5).alias("squares"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.array_max("embedding").cast("double"), 6).alias("most"))


@query("dot_products_embeddings", "select a.vec_id, round(list_dot_product(a.embedding::double[], b.embedding::double[]), 5) as dot from embeddings a join embeddings b on b.vec_id = a.vec_id + 1")
def dot_products_embeddings(s, d):
    e = T(s, d, "embeddings")
    nxt = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other"))
    dot = F.aggregate(F.zip_with("embedding", "other", lambda x, y: x.cast("double") * y), F.lit(0.0), lambda a, v: a + v)
    return e.join(nxt, "vec_id").select("vec_id", F.round(dot, 5).alias("dot"))


@query("cosine_udf_embeddings", "select a.vec_id, round(list_cosine_similarity(a.embedding::double[], b.embedding::double[]), 5) as cos from embeddings a join embeddings b on b.vec_id = a.vec_id + 1")
def cosine_udf_embeddings(s, d):
    e = T(s, d, "embeddings")
    nxt = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other"))
    return e.join(nxt, "vec_id").select("vec_id", F.round(udfs.cosine_udf("embedding", "other"), 5).alias("cos"))


@query("norm_udaf_w4", f"with {sql.matrix('w4')} select col, round(norm, 6) as norm from c")
def norm_udaf_w4(s, d):
    return matrix.to_triplets(workloads.matrix(s, d, "w4")).groupBy("col").agg(F.round(udfs.l2_norm_udaf("val"), 6).alias("norm"))


@query("block_source", "select count(c_custkey) as n, case when count(c_custkey) > 0 then 10::bigint end as entries from customer")
def block_source(s, d):
    """The block construction over the customers: a row for each, whose entries are the ten columns of its group."""
    from tallgram.sources.block_source import BlockMatrixSource

    s.dataSource.register(BlockMatrixSource)
    m = s.read.format("block_matrix").option("path", f"{d}/customer.parquet").option("key", "c_custkey").option("row_max", 10).load()
    return m.agg(F.count("*").alias("n"), F.max(F.size("entries")).cast("long").alias("entries"))


@query("labelled_word_pairs", f"with t0 as ({sql.LABELLED['w2c']}), l as (select doc_id from labels where quality = 1) select count(*) as entries, count(distinct row_id) as documents from t0 semi join l on row_id = doc_id")
def labelled_word_pairs(s, d):
    """Words of documents of good quality only: a matrix restricted by a semi-join before it is built."""
    good = T(s, d, "labels").where("quality = 1").select(F.col("doc_id").alias("row_id"))
    return workloads.words_by_document(s, d).join(good, "row_id", "left_semi").agg(F.count("*").alias("entries"), F.count_distinct("row_id").alias("documents"))


@query("restricted_similarity_w2b", f"with {_COS_W2B}, p as (select i, j from e where i < 10) select i, j, round(e.cos, 6) as cos from e join p using (i, j)")
def restricted_similarity_w2b(s, d):
    m = workloads.matrix(s, d, "w2b")
    wanted = gram.all_pairs(m).where("i < 10").select("i", "j").distinct()
    return _round(similarity.exact_of(m, wanted).select("i", "j", "cos"))


# --- sources, sinks and the rest of the surface ---


def _shared(s) -> str:
    from tallgram.queries.streams import _folder

    return _folder(s)


def _triplets_from(s, d, fmt: str) -> DataFrame:
    from tallgram.sources import files

    path = f"{_shared(s)}/triplets"
    files.save_triplets(workloads.triplets(s, d, "w4c"), path, fmt)
    return files.load_triplets(s, path, fmt)


for _fmt in ("csv", "json", "orc", "text", "parquet"):
    add(f"triplets_{_fmt}_w4c", lambda s, d, f=_fmt: _triplets_from(s, d, f), f"with {sql.matrix('w4c')} select row_id, col, val from m")


@query("saved_rows_w4", f"with {sql.matrix('w4')} select row_id, count(*)::integer as n, min(col) as first from m group by row_id")
def saved_rows_w4(s, d):
    """Row form stored in folders by the size of the row, and read back without a shuffle."""
    from tallgram.sources import files

    path = f"{_shared(s)}/rows"
    files.save_rows(workloads.matrix(s, d, "w4").withColumn("n", F.size("entries")), path, "n")
    return s.read.parquet(path).select("row_id", F.size("entries").alias("n"), F.element_at("entries", 1)["col"].alias("first"))


@query("saved_pairs_w2b", f"with {_COS_W2B} select i, j, round(cos, 6) as cos from e where i between 20 and 60")
def saved_pairs_w2b(s, d):
    """Pairs in folders of first columns: a range of columns reads its folders only."""
    from tallgram.sources import files

    path = f"{_shared(s)}/pairs"
    files.save_pairs(_cosines(s, d).select("i", "j", "cos"), path, 16)
    return _round(files.load_pairs(s, path, 20, 60, 16))


@query("bucketed_rows_w4c", f"with {sql.matrix('w4c')} select row_id, count(*) as n, sum(val) as total from m group by row_id")
def bucketed_rows_w4c(s, d):
    """A table bucketed by row, grouped by row without an exchange."""
    import uuid

    from tallgram.sources import files

    name = f"bucketed_{uuid.uuid4().hex}"
    files.save_bucketed(workloads.triplets(s, d, "w4c"), name, 8)
    return s.table(name).groupBy("row_id").agg(F.count("*").alias("n"), F.sum("val").alias("total"))


@query("stable_row_ids", "select count(*) as n, count(*) as ids from nation")
def stable_row_ids(s, d):
    from tallgram.sources.tables import with_row_ids

    ids = with_row_ids(T(s, d, "nation").select("n_nationkey", F.col("_metadata")))
    return ids.agg(F.count("*").alias("n"), F.count_distinct("file", "row").alias("ids"))


@query("sql_parameters", "select p_partkey, p_size from part where p_size between 10 and 20 and p_brand = 'Brand#11'")
def sql_parameters(s, d):
    T(s, d, "part").createOrReplaceTempView("part_view")
    return s.sql("select p_partkey, p_size from part_view where p_size between :low and :high and p_brand = :brand", args={"low": 10, "high": 20, "brand": "Brand#11"})


@query("sql_unit_draw_w4", f"with {sql.matrix('w4')} select count(*) as n, true as inside from m")
def sql_unit_draw_w4(s, d):
    """The registered draw is the one of the methods, and lies in [0, 1)."""
    from tallgram.functions.draws import unit_draw

    udfs.register(s)
    rows = matrix.to_triplets(workloads.matrix(s, d, "w4")).select("row_id", "col", F.expr("unit_draw(7, row_id, cast(col as bigint), cast(col as bigint))").alias("u"))
    same = (F.col("u") == unit_draw(7, F.col("row_id"), F.col("col").cast("long"), F.col("col").cast("long"))) & F.col("u").between(0, 0.9999999999999999)
    return rows.agg(F.count("*").alias("n"), F.bool_and(same).alias("inside"))


@query("json_out_events", "select event_id, '{\"t\":\"' || event_type || '\",\"u\":' || user_id || '}' as doc, 'STRUCT<k: BIGINT>' as shape from events")
def json_out_events(s, d):
    shape = F.schema_of_json(F.lit('{"k": 1}'))
    return T(s, d, "events").select("event_id", F.to_json(F.struct(F.col("event_type").alias("t"), F.col("user_id").alias("u"))).alias("doc"), shape.alias("shape"))


@query("local_sort_w4c", f"with {sql.matrix('w4c')} select row_id, max(val) as heaviest from m group by row_id")
def local_sort_w4c(s, d):
    """Rows sorted inside their partitions, so the first of each row is its heaviest entry: no exchange but the one by row."""
    t = workloads.triplets(s, d, "w4c").repartition("row_id").sortWithinPartitions("row_id", F.desc("val"))
    return t.groupBy("row_id").agg(F.first("val").alias("heaviest"))


@query("grouped_map_centred_w4c", f"with {sql.matrix('w4c')}, a as (select col, avg(val) as mean from m group by col) select row_id, col, round(val - mean, 6) as centred from m join a using (col)")
def grouped_map_centred_w4c(s, d):
    """Each column less its mean, one group at a time. Groups are columns; the built-in way is a window or a join with the means."""
    import pyarrow as pa
    import pyarrow.compute as pc

    def centred(rows: pa.Table) -> pa.Table:
        val = rows.column("val")
        return pa.table({"row_id": rows.column("row_id"), "col": rows.column("col"), "centred": pc.subtract(val, pc.mean(val))})

    return _round(workloads.triplets(s, d, "w4c").groupBy("col").applyInArrow(centred, "row_id long, col int, centred double"))


@query("cogroup_clicks_purchases", "select coalesce(a.user_id, b.user_id) as user_id, coalesce(a.n, 0) as clicks, coalesce(b.n, 0) as purchases from (select user_id, count(*) as n from events where event_type = 'click' group by 1) a full join (select user_id, count(*) as n from events where event_type = 'purchase' group by 1) b on a.user_id = b.user_id")
def cogroup_clicks_purchases(s, d):
    import pyarrow as pa

    def counts(left: pa.Table, right: pa.Table) -> pa.Table:
        one = left if left.num_rows else right
        return pa.table({"user_id": one.column("user_id").slice(0, 1), "clicks": pa.array([left.num_rows], pa.int64()), "purchases": pa.array([right.num_rows], pa.int64())})

    e = T(s, d, "events").select("user_id", "event_type")
    return e.where("event_type = 'click'").groupBy("user_id").cogroup(e.where("event_type = 'purchase'").groupBy("user_id")).applyInArrow(counts, "user_id long, clicks long, purchases long")
