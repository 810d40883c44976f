"""SQL that gives the same rows as the queries of the engine, on the same tables."""

from __future__ import annotations

from coltypes.functions.exprs import GENERIC
from coltypes.sources import collection as C
from coltypes.sources import tables as T

#: Tables whose text columns are short names and codes; vectors and samples of the checked queries use all their rows.
RELATIONAL = ("region", "nation", "customer", "supplier", "part", "orders")


def hash32(x: str) -> str:
    return f"cast(('0x' || substr(md5({x}), 1, 8))::ubigint as bigint)"


def norm(x: str) -> str:
    return f"regexp_replace(regexp_replace(lower({x}), '^[a-z]_', ''), '[^a-z0-9]', '', 'g')"


def _cell(column: str, letter: str) -> str:
    return f"strftime({column}, '%Y-%m-%d %H:%M:%S')" if letter == "t" else f"cast({column} as varchar)"


def long_sql(tables=tuple(T.SCHEMAS), kinds: str = "nst") -> str:
    """(column_id, table_id, header, ordinal, kind, value, num) of all cells."""
    parts = []
    for t in tables:
        for k, (c, letter) in enumerate(T.columns_of(t)):
            if letter in kinds:
                keep = f"{c} is not null" + (f" and trim({c}) <> ''" if letter == "s" else "")
                num = f"cast({c} as double)" if letter == "n" else "cast(null as double)"
                parts.append(f"select '{t}.{c}' column_id, '{t}' table_id, '{c}' header, {k} ordinal, '{T.kind_of(letter)}' kind, {_cell(c, letter)} as value, {num} num from {t} where {keep}")
    return " union all ".join(parts)


def catalog_sql(tables=tuple(T.SCHEMAS)) -> str:
    rows = [f"('{t}.{c}', '{t}', '{c}', {k}, '{T.kind_of(x)}', '{C.TYPE_OF[f'{t}.{c}']}')" for t in tables for k, (c, x) in enumerate(T.columns_of(t))]
    return "select * from (values " + ", ".join(rows) + ") v(column_id, table_id, header, ordinal, kind, truth)"


LONG, CATALOG = long_sql(), catalog_sql()
#: The catalog of columns that hold a value, and the queries over it.
HELD = f"select * from ({CATALOG}) where column_id in (select column_id from ({LONG}) where num is null or not isnan(num))"
HELD_QUERIES = ("calls_by_phase", "calls_by_role_cube", "candidates_name", "candidates_value", "cluster_order", "confusion", "context_profile", "cost_per_k", "coverage")
TEXTS = f"select distinct column_id, value from ({long_sql(RELATIONAL, 'st')})"
NUMS = long_sql(kinds="n")
ANN = f"select column_id, kind, case when {hash32('column_id')} % 7 = 0 then 'Wrong ' || truth else truth end label, case when {hash32('column_id')} % 2 = 0 then 'discovery' else 'rest' end phase, truth from ({CATALOG}) where {hash32('column_id')} % 5 <> 0"
CALLS = f"select 'discovery' as role, 'discovery' phase, column_id target, header || ' of ' || table_id prompt, '{{\"answer\": [\"' || truth || '\"]}}' response from ({CATALOG})"
TOKENS = f"select role, phase, target, cast(ceil(length(prompt) / 4.0) as bigint) in_tokens, cast(ceil(length(response) / 4.0) as bigint) out_tokens from ({CALLS})"
MEMBERS = f"select column_id, {norm('header')} seed_cluster from ({CATALOG}) where {norm('header')} in (select {norm('header')} from ({CATALOG}) group by 1 having count(*) > 1)"



def gram_vectors(src: str) -> str:
    """(id, b, w): unit n-gram vectors of rows (id, txt), sparse."""
    grams = f"select id, unnest(list_concat(list_transform(range(1, length(m)), lambda i: substr(m, i, 2)), list_transform(range(1, length(m) - 1), lambda i: substr(m, i, 3)))) gram from (select id, '^' || txt || '$' m from {src})"
    return f"select id, b, c / sqrt(sum(c * c) over (partition by id)) w from (select id, {hash32('gram')} % 256 b, cast(count(*) as double) c from ({grams}) group by 1, 2)"


HEADERS = f"(select distinct {norm('header')} id, {norm('header')} txt from ({CATALOG}))"
TEXT_MEAN = f"select v.column_id, w.b pos, sum(w.w) / any_value(n.n) x from ({TEXTS}) v join ({gram_vectors(f'(select distinct value id, value txt from ({TEXTS}))')}) w on v.value = w.id join (select column_id, count(*) n from ({TEXTS}) group by 1) n on n.column_id = v.column_id group by 1, 2"


def sparse_pairs(vectors: str, key: str, pos: str, val: str, tau: float) -> str:
    """(i, j, sim) at or above tau from a sparse vector table."""
    return f"with v as ({vectors}), u as (select {key} k, {pos} p, {val} / nullif(sqrt(sum({val} * {val}) over (partition by {key})), 0) x from v) select a.k i, b.k j, round(sum(a.x * b.x), 6) sim from u a join u b on a.p = b.p and a.k < b.k group by 1, 2 having round(sum(a.x * b.x), 6) >= {tau}"


MOMENTS = f"select column_id, count(num) n, avg(num) mean, stddev_pop(num) deviation, min(num) lo, max(num) hi from ({NUMS}) group by 1"


def bins_sql(minmax: bool = False) -> str:
    share = "case when hi > lo then round((num - lo) / (hi - lo), 9) else 0.0 end" if minmax else "((case when deviation > 0 then round((num - mean) / deviation, 9) else 0.0 end) + 4) / 8"
    return f"select column_id, bin, count(*) / cast(any_value(n) as double) density from (select c.column_id, n, cast(greatest(0, least(99, floor(({share}) * 100))) as int) bin from ({NUMS}) c join ({MOMENTS}) m on m.column_id = c.column_id) group by 1, 2"


STRATA = f"select column_id, value, length(value) len, row_number() over (partition by column_id, length(value) order by md5(value || '#0'), value) turn, count(*) over (partition by column_id, length(value)) size from ({TEXTS})"


def stratified(k: int) -> str:
    return f"select column_id, value, len from (select *, row_number() over (partition by column_id order by turn, size desc, len) place from ({STRATA})) where place <= {k}"


def proportional(k: int) -> str:
    return f"""with v as ({STRATA}), s as (select distinct column_id, len, size from v),
    p as (select * from (select *, row_number() over (partition by column_id order by size desc, len) place from s) where place <= {k}),
    e as (select *, greatest(0, {k} - count(*) over (partition by column_id)) spare, greatest(0, {k} - count(*) over (partition by column_id)) * (size - 1) / cast(greatest(sum(size - 1) over (partition by column_id), 1) as double) exact from p),
    w as (select *, floor(exact) whole, exact - floor(exact) rest from e),
    q as (select *, 1 + whole + case when row_number() over (partition by column_id order by round(rest, 9) desc, len) <= spare - sum(whole) over (partition by column_id) then 1 else 0 end quota from w)
    select v.column_id, v.value, v.len from v join q on q.column_id = v.column_id and q.len = v.len where v.turn <= q.quota"""


CONTEXT = f"""with m as ({MEMBERS}), c as ({CATALOG}), src as (select distinct m.seed_cluster, c.table_id from m join c using (column_id)),
 tot as (select seed_cluster, count(*) of_tables from src group by 1),
 beside as (select s.seed_cluster, s.table_id, c.header from src s join c using (table_id) where not exists (select 1 from m where m.column_id = c.column_id and m.seed_cluster = s.seed_cluster)),
 cnt as (select seed_cluster, header, count(distinct table_id) n_tables from beside group by 1, 2),
 r as (select *, row_number() over (partition by seed_cluster order by n_tables desc, header) as "rank" from cnt)
 select r.seed_cluster, header, n_tables, of_tables, "rank" from r join tot on tot.seed_cluster = r.seed_cluster where "rank" <= 5"""
TYPED = f"select distinct m.seed_cluster, c.kind, c.truth label from ({MEMBERS}) m join ({CATALOG}) c using (column_id)"
INDEXED = f"select distinct x.value, t.label from ({LONG}) x join ({MEMBERS}) m on m.column_id = x.column_id join ({TYPED}) t on t.seed_cluster = m.seed_cluster where x.kind = 'text'"
OPEN = f"select * from ({CATALOG}) where column_id not in (select column_id from ({ANN}))"
VERDICTS = f"select column_id, label, label = truth as valid from ({ANN})"
CONFUSION = f"select cast(count(case when a.label is not null and t.truth is not null then 1 end) as bigint) tp, cast(count(case when t.truth is null then 1 end) as bigint) fp, cast(count(case when a.label is null then 1 end) as bigint) fn from ({ANN}) a full join (select column_id, truth from ({CATALOG})) t on t.column_id = a.column_id and t.truth = a.label"
PAIRS = f"select a.column_id left_id, b.column_id right_id from ({CATALOG}) a join ({CATALOG}) b on a.truth = b.truth and a.column_id < b.column_id and a.table_id <> b.table_id"
PAIR_LABELS = f"select p.left_id, p.right_id, l.label l, r.label r from ({PAIRS}) p left join ({ANN}) l on l.column_id = p.left_id left join ({ANN}) r on r.column_id = p.right_id"


def candidates(view: str, source: str) -> str:
    return f"with m as (select column_id, {view} c from ({CATALOG})), known as (select distinct m.c, a.label from m join ({ANN}) a using (column_id)) select m.column_id, k.label, '{source}' as source from m join known k on k.c = m.c where m.column_id in (select column_id from ({OPEN}))"


def slices_sql(name: str) -> str:
    parts = []
    for base, keys in C.SLICES[name].items():
        key = ", ".join(f"coalesce(cast({k} as varchar), 'null')" for k in keys)
        n = [x for _, x in T.columns_of(base)]
        parts.append(f"select concat_ws('_', '{base}', {key}) table_id, {len(n)} w, {sum(x == 'n' for x in n)} num, {sum(x != 'n' for x in n)} txt, count(*) n_rows from {base} group by 1")
    return " union all ".join(parts)




def multi_sql() -> str:
    """(column_id, value, n): the values of the columns of mixed types."""
    parts = []
    for k, (header, sources) in enumerate(C.MULTI, 1):
        for source in sources.split():
            base, column = source.split(".")
            parts.append(f"select distinct 'multi_{k:02d}.{header}' column_id, {_cell(column, dict(T.columns_of(base))[column])} as value from {base} where {column} is not null")
    return "select column_id, value, count(*) n from (" + " union all ".join(parts) + ") group by 1, 2"


def shown_sql(k: int) -> str:
    """Lengths and values that samples of k values of the mixed columns show."""
    v = f"select column_id, value, n, row_number() over (partition by column_id order by md5(value || '#0'), value) u, row_number() over (partition by column_id order by n desc, value) f, row_number() over (partition by column_id, length(value) order by md5(value || '#0'), value) turn, count(*) over (partition by column_id, length(value)) size from ({multi_sql()})"
    v = f"select *, row_number() over (partition by column_id order by turn, size desc, length(value)) s from ({v})"
    count = "cast(sum(l) as bigint) lengths, cast(sum(c) as bigint) n_values from (select column_id, count(distinct length(value)) l, count(*) c from"
    return " union all ".join(f"select '{way}' way, {count} ({v}) where {place} <= {k} group by 1)" for way, place in (("stratified", "s"), ("uniform", "u"), ("frequency", "f")))


LABEL_GRAMS = gram_vectors(f"(select distinct lower(label) id, lower(label) txt from ({ANN}))")
PAIR_SIMILARITY = f"""with w as ({LABEL_GRAMS}), a as ({ANN}), s as (select x.id i, y.id j, sum(x.w * y.w) sim from w x join w y on x.b = y.b group by 1, 2)
 select round(avg(coalesce(s.sim, 0)), 6) similarity, count(*) n_typed from ({PAIRS}) p join a l on l.column_id = p.left_id join a r on r.column_id = p.right_id left join s on s.i = lower(l.label) and s.j = lower(r.label)"""
DRIFT = """with m as (select avg(value) mean, stddev_pop(value) deviation from events), b as (select time_bucket(interval '1 day', ts) w, cast(greatest(0, least(99, floor((round((value - mean) / deviation, 9) + 4) / 8 * 100))) as int) bin from events, m where value is not null),
 d as (select w, bin, count(*) c from b group by 1, 2), a as (select bin, count(*) c from b group by 1)
 select w, round(sum(d.c * a.c) / (sqrt(sum(d.c * d.c)) * (select sqrt(sum(c * c)) from a)), 6) similarity from d join a on a.bin = d.bin group by 1"""

GENERIC_SQL = ", ".join(f"'{g}'" for g in GENERIC)

SQL = {
    "column_catalog": f"select c.column_id, c.table_id, c.header, c.ordinal, c.kind, coalesce(s.n, 0) n_cells, coalesce(s.d, 0) n_distinct from ({CATALOG}) c left join (select column_id, count(*) n, count(distinct value) d from ({LONG}) group by 1) s on s.column_id = c.column_id",
    "column_values_orders": f"select column_id, kind, value, count(*) n, length(value) len from ({long_sql(('orders',), 'st')}) group by 1, 2, 3",
    "collection_stats": f"select count(*) n_tables, min(w) min_columns, max(w) max_columns, min(n_rows) min_rows, max(n_rows) max_rows, cast(sum(num) as bigint) num_columns, cast(sum(txt) as bigint) text_columns from ({slices_sql('OPS')})",
    "distinct_counts": f"select column_id, count(distinct value) n_distinct from ({LONG}) group by 1",
    "length_profile": f"select column_id, length(value) len, count(*) n_values from (select distinct column_id, value from ({long_sql(kinds='st')})) group by 1, 2",
    "header_ngram_vectors": f"select id header_key, cast(b as int) bucket, round(w, 6) w from ({gram_vectors(HEADERS)})",
    "text_column_vectors": f"select column_id, cast(pos as int) pos, round(x, 6) x from ({TEXT_MEAN})",
    "numeric_moments": f"select column_id, n, round(mean, 6) mean, round(deviation, 6) deviation, round(lo, 6) lo, round(hi, 6) hi from ({MOMENTS})",
    "numeric_zscore_bins": f"select column_id, bin, round(density, 6) density from ({bins_sql()})",
    "numeric_histogram_minmax": f"select column_id, bin, round(density, 6) density from ({bins_sql(True)})",
    "header_pairs_099": sparse_pairs(f"select column_id || '' k, b p, w x from ({gram_vectors(HEADERS)}) g join (select column_id, {norm('header')} hk from ({CATALOG})) c on c.hk = g.id", "k", "p", "x", 0.99),
    "numeric_pairs_090": sparse_pairs(bins_sql(), "column_id", "bin", "density", 0.9),
    "text_pairs_075": sparse_pairs(TEXT_MEAN, "column_id", "pos", "x", 0.75),
    "embedding_pairs_030": "select a.vec_id i, b.vec_id j, round(list_cosine_similarity(cast(a.embedding as double[]), cast(b.embedding as double[])), 6) sim from embeddings a join embeddings b on a.vec_id < b.vec_id where round(list_cosine_similarity(cast(a.embedding as double[]), cast(b.embedding as double[])), 6) >= 0.3",
    "jaccard_pairs": f"with v as (select distinct column_id, value from ({long_sql(RELATIONAL)})), s as (select column_id, count(*) n from v group by 1), b as (select x.column_id i, y.column_id j, count(*) c from v x join v y on x.value = y.value and x.column_id < y.column_id group by 1, 2) select i, j, round(c / cast(si.n + sj.n - c as double), 6) sim from b join s si on si.column_id = i join s sj on sj.column_id = j where round(c / cast(si.n + sj.n - c as double), 6) >= 0.01",
    "seed_clusters_given": f"with b as (select column_id, {norm('header')} name_cluster, kind value_cluster from ({CATALOG})), s as (select name_cluster, value_cluster, min(column_id) seed_cluster from b group by 1, 2 having count(*) >= 2) select b.column_id, name_cluster, value_cluster, seed_cluster from b join s using (name_cluster, value_cluster)",
    "stratified_sample_small_k": stratified(3),
    "stratified_sample_large_k": stratified(40),
    "stratified_sample_proportional": proportional(10),
    "uniform_sample": f"select column_id, value from (select *, row_number() over (partition by column_id order by md5(value || '#0'), value) place from ({TEXTS})) where place <= 10",
    "frequency_sample": f"select column_id, value, n from (select column_id, value, count(*) n, row_number() over (partition by column_id order by count(*) desc, value) place from ({long_sql(RELATIONAL, 'st')}) group by 1, 2) where place <= 10",
    "dense_rows": "select o_orderkey, o_orderstatus, o_orderpriority from orders order by md5(concat_ws('|', cast(o_orderkey as varchar), o_orderstatus, o_orderpriority, '0')) limit 10",
    "context_profile": CONTEXT,
    "index_extend": INDEXED,
    "index_lookup": f"select distinct v.column_id, x.label from (select distinct column_id, value from ({long_sql(kinds='st')})) v join ({INDEXED}) x on x.value = v.value",
    "index_fallback": f"select c.column_id, t.label from ({CATALOG}) c join (select distinct kind, label from ({TYPED})) t on t.kind = c.kind where c.column_id not in (select v.column_id from ({long_sql(kinds='st')}) v join ({INDEXED}) x on x.value = v.value)",
    "cluster_sharing": f"with v as (select distinct m.seed_cluster k, x.value from ({LONG}) x join ({MEMBERS}) m on m.column_id = x.column_id) select distinct p.k a, q.k b from v p join v q on p.value = q.value and p.k <> q.k",
    "cluster_order": f"select seed_cluster, count(*) n_columns, min(column_id) as \"first\" from ({MEMBERS}) group by 1",
    "seed_propagation": f"select m.column_id, t.label, 'discovery' phase, 'seed' as source, 0.9::double threshold from ({MEMBERS}) m join ({TYPED}) t on t.seed_cluster = m.seed_cluster",
    "parse_answers": f"select target, case when length(label) > 0 and lower(label) not in ({GENERIC_SQL}) then label else '' end labels from (select target, trim(json_extract_string(response, '$.answer[0]')) label from ({CALLS}))",
    "candidates_name": candidates(norm("header"), "name"),
    "candidates_value": candidates("kind", "value"),
    "candidates_index": f"select distinct v.column_id, x.label, 'index' as source from (select distinct column_id, value from ({long_sql(kinds='st')})) v join ({INDEXED}) x on x.value = v.value where v.column_id in (select column_id from ({OPEN}))",
    "type_aggregation": f"select column_id, label, 'rest' phase, min(source) as source, 0.9::double threshold from (select column_id, label, 'name' as source, kind from ({ANN}) union all select column_id, label, 'index' as source, kind from ({ANN})) where kind = 'text' or source = 'name' group by 1, 2",
    "token_usage": f"select cast(sum(in_tokens) as bigint) in_tokens, cast(sum(out_tokens) as bigint) out_tokens, count(*) n_calls from ({TOKENS})",
    "calls_by_phase": f"select role, phase, count(*) n_calls, cast(sum(in_tokens) as bigint) in_tokens, cast(sum(out_tokens) as bigint) out_tokens from ({TOKENS}) group by rollup(role, phase)",
    "cost_per_k": f"select round((select (sum(in_tokens) * 2.0 + sum(out_tokens) * 8.0) / 1e6 from ({TOKENS})) * 1000 / (select count(distinct column_id) from ({ANN})), 6) cost_per_k",
    "coverage": f"select round(avg(case when a.column_id is not null then 1.0 else 0.0 end), 6) coverage from ({CATALOG}) c left join (select distinct column_id from ({ANN})) a on a.column_id = c.column_id",
    "type_count": f"select count(distinct label) n_types from ({ANN})",
    "hit_rate": f"select round(avg(h), 6) hit_rate from (select column_id, max(case when valid then 1.0 else 0.0 end) h from ({VERDICTS}) group by 1)",
    "judged_precision": f"select round(avg(case when valid then 1.0 else 0.0 end), 6) judged_precision from ({VERDICTS})",
    "confusion": CONFUSION,
    "prf": f"select tp, fp, fn, round(tp / cast(tp + fp as double), 6) p, round(tp / cast(tp + fn as double), 6) r, round(2 * tp / cast(2 * tp + fp + fn as double), 6) f1 from ({CONFUSION})",
    "prf_by_phase": f"select phase, tp, fp, fn, round(tp / cast(tp + fp as double), 6) p, round(tp / cast(tp + fn as double), 6) r, round(2 * tp / cast(2 * tp + fp + fn as double), 6) f1 from (select phase, cast(count(case when label = truth then 1 end) as bigint) tp, cast(count(case when label <> truth then 1 end) as bigint) fp, cast(count(case when label <> truth then 1 end) as bigint) fn from ({ANN}) group by 1)",
    "representatives": f"select distinct phase, column_id from (select case when phase = 'discovery' then 'discovery' else 'annotation' end phase, label, column_id, row_number() over (partition by case when phase = 'discovery' then 'discovery' else 'annotation' end, label order by md5(column_id), column_id) place from ({ANN})) where place = 1",
    "redundancy": f"select count(distinct label) n_types from ({ANN}) where phase = 'discovery'",
    "synthetic_truth": f"with found as (select column_id, label from ({VERDICTS}) where valid), missed as (select c.column_id, c.truth from ({CATALOG}) c left join found f on f.column_id = c.column_id and f.label = c.truth where f.column_id is null) select column_id, label from found union all select column_id, 'Other_' || row_number() over (partition by column_id order by truth) from missed",
    "pair_agreement": f"select round(100 * avg(case when l = r then 1.0 else 0.0 end), 6) pct_shared, round(100 * avg(case when l = r then 1.0 else 0.0 end), 6) pct_same, count(*) n_pairs from ({PAIR_LABELS})",
    "pair_agreement_annotated": f"select round(100 * avg(case when l = r then 1.0 else 0.0 end), 6) pct_shared, round(100 * avg(case when l = r then 1.0 else 0.0 end), 6) pct_same, count(*) n_pairs from ({PAIR_LABELS}) where l is not null and r is not null",
    "pair_similarity": PAIR_SIMILARITY,
    "exp_sampling": shown_sql(4),
    "running_tokens": f"select target, in_tokens, cast(sum(in_tokens) over (order by target) as bigint) so_far from ({TOKENS})",
    "drift_by_day": DRIFT,
    "stream_deduplicated": "select event_type, count(distinct event_id) n from events group by 1",
    "calls_by_role_cube": f"select role, phase, count(*) n_calls from ({TOKENS}) group by cube(role, phase)",
    "table_rows_regions": "select 'nation' table_id, n_nationkey nk, n_name nn, n_regionkey rk from nation order by md5(concat_ws('|', 'nation', cast(n_nationkey as varchar), n_name, cast(n_regionkey as varchar), '0')) limit 3",
    "overlap_filter": f"select left_id, right_id from ({PAIR_LABELS}) where l = r",
    "suspect_columns": f"select column_id, count(distinct label) n_types from (select column_id, label from ({ANN}) union all select column_id, truth from ({ANN})) group by 1 having count(distinct label) > 1",
    "stream_windows": "select time_bucket(interval '1 day', ts) w, event_type, count(*) n, round(sum(value), 6) total from events group by 1, 2",
    "stream_sessions": "with g as (select user_id, ts, value, case when ts - lag(ts) over (partition by user_id order by ts) >= interval '12 hours' or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end s from events), k as (select *, sum(s) over (partition by user_id order by ts rows unbounded preceding) sid from g) select user_id, min(ts) started, count(*) n, round(sum(value), 6) total from k group by user_id, sid",
}
SQL |= {name: SQL[name].replace(f"({CATALOG})", f"({HELD})") for name in HELD_QUERIES}
