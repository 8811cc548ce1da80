"""SQL pieces of the oracles: workload matrices, norms, draws and sums as common table expressions."""

from __future__ import annotations

_WORDS = r"unnest(list_distinct(regexp_extract_all(lower(text), '\p{L}+')))"

#: (row_id, label, val) of each workload.
LABELLED = {
    "w1": "select distinct cast(floor(epoch_us(ts) / 3600000000) as bigint) * 4294967296 + cast('0x' || substr(md5(coalesce(event_type, '')), 1, 8) as bigint) as row_id, user_id as label, 1.0::double as val from events",
    "w1b": "select distinct l_partkey as row_id, o_custkey as label, 1.0::double as val from lineitem join orders on l_orderkey = o_orderkey",
    "w2": f"select row_id, label, 1.0::double as val from (select conv_id * 16777216 + turn as row_id, {_WORDS} as label from conversations) qualify count(*) over (partition by label) >= 5",
    "w2b": f"select row_id, label, 1.0::double as val from (select conv_id * 16777216 + turn as row_id, {_WORDS} as label from conversations) qualify count(*) over (partition by label) >= 20",
    "w2c": f"select row_id, label, 1.0::double as val from (select doc_id as row_id, {_WORDS} as label from documents) qualify count(*) over (partition by label) >= 20",
    "w3": "select distinct user_id * 1048576 + date_diff('day', date '1970-01-01', ts::date) as row_id, cast(json_extract_string(props, '$.k') as integer) as label, 1.0::double as val from events where json_extract_string(props, '$.k') is not null",
    "w10": f"select row_id, label, 1.0::double as val from (select doc_id as row_id, {_WORDS} as label from documents where doc_id in (select doc_id from labels where toxic = 1)) qualify count(*) over (partition by label) >= 10",
    "w4": "select distinct l_orderkey as row_id, p_brand as label, 1.0::double as val from lineitem join part on l_partkey = p_partkey",
    "w4b": "select distinct l_orderkey as row_id, l_suppkey as label, 1.0::double as val from lineitem",
    "w4c": "select l_orderkey as row_id, l_suppkey as label, sum(l_quantity) as val from lineitem group by all",
    "w4d": "select distinct l_orderkey as row_id, l_partkey as label, 1.0::double as val from lineitem",
}


def matrix(name: str) -> str:
    """CTEs ending in m(row_id, col, val) and c(col, nnz, sumsq, norm)."""
    if name == "w5":
        m = "m as (select vec_id as row_id, (unnest(range(len(embedding))))::int as col, unnest(embedding)::double as val from embeddings)"
    else:
        m = f"t as ({LABELLED[name]}), d as (select label, row_number() over (order by label) - 1 as col from (select distinct label from t)), m as (select t.row_id, d.col::int as col, t.val from t join d using (label) where t.val <> 0)"
    return f"{m}, c as (select col, count(*) as nnz, sum(val * val) as sumsq, sqrt(sum(val * val)) as norm from m group by col)"


PAIRS = "q as (select a.row_id, a.col as i, b.col as j, a.val as x, b.val as y, ca.norm as ni, cb.norm as nj from m a join m b on a.row_id = b.row_id and a.col < b.col join c ca on ca.col = a.col join c cb on cb.col = b.col)"


def draw(seed: int, *keys: str) -> str:
    text = "concat_ws('|', '" + str(seed) + "', " + ", ".join(keys) + ")"
    return f"(cast(('0x' || substr(md5({text}), 1, 13)) as bigint)::double / 4503599627370496::double)"


def real(x: float) -> str:
    return f"{x!r}::double"


def with_pairs(name: str, body: str) -> str:
    return f"with {matrix(name)}, {PAIRS} {body}"


def pair_kept(gamma: float | str, seed: int) -> str:
    """gamma: a number, or SQL of one."""
    if isinstance(gamma, str):
        return f"(ni * nj <= {gamma} or {draw(seed, 'row_id', 'i', 'j')} < {gamma} / (ni * nj))"
    return f"(ni * nj <= {real(gamma)} or {draw(seed, 'row_id', 'i', 'j')} < {real(gamma)} / (ni * nj))"


def sampled(name: str, gamma: float, seed: int) -> str:
    g = real(gamma)
    return with_pairs(name, f"select i, j, round(sum(x * y) / least({g}, max(ni * nj)), 6) as cos, round(sum(x * y) / least({g}, max(ni * nj)) * max(ni * nj), 6) as dot, count(*) as n_kept, round(least(1.0::double, {g} / max(ni * nj)), 9) as p, {g} >= max(ni * nj) as is_exact from q where {pair_kept(gamma, seed)} group by i, j")


def staged_weight(gamma: float) -> str:
    s = f"sqrt({real(gamma)})"
    return f"(least({s}, ni) * least({s}, nj))"


def head_kept(gamma: float, seed: int, salt: str, col: str, norm: str) -> str:
    s = f"sqrt({real(gamma)})"
    return f"({norm} <= {s} or {draw(seed, repr(salt), 'row_id', col)} < {s} / {norm})"


def staged_kept(gamma: float, seed: int) -> str:
    s = f"sqrt({real(gamma)})"
    second = f"(nj <= {s} or {draw(seed, repr('second'), 'row_id', 'i', 'j')} < {s} / nj)"
    return f"{head_kept(gamma, seed, 'first', 'i', 'ni')} and {second}"


def staged_kept_back(gamma: float, seed: int) -> str:
    """The same pair drawn from its other side."""
    s = f"sqrt({real(gamma)})"
    second = f"(ni <= {s} or {draw(seed, repr('second'), 'row_id', 'j', 'i')} < {s} / ni)"
    return f"{head_kept(gamma, seed, 'first', 'j', 'nj')} and {second}"


def thinned_kept(gamma: float, seed: int) -> str:
    return f"{head_kept(gamma, seed, 'entry', 'i', 'ni')} and {head_kept(gamma, seed, 'entry', 'j', 'nj')}"
