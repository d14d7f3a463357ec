"""Queries of the operators around the engine: sources, joins, aggregates, windows, functions, UDFs.

Where both engines read the same SQL, one text serves for both: {table} is the table.
"""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import functions as F

from tidelabel.functions.rand import uniform, uniform_sql
from tidelabel.sources.tables import load

QUERIES, ORACLES = {}, {}


def same(name: str, spark_sql: str, duck_sql: str | None = None) -> None:
    tables = sorted(set(re.findall(r"\{(\w+)\}", spark_sql)))
    QUERIES[name] = lambda spark, sf_dir: spark.sql(spark_sql, **{t: load(spark, sf_dir, t) for t in tables})
    ORACLES[name] = re.sub(r"\{(\w+)\}", r"\1", spark_sql) if duck_sql is None else duck_sql


def query(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return add


# sources and filters
same("scan_prune_lineitem", "select l_orderkey, l_quantity from {lineitem} where l_quantity > 45 and l_discount between 0.05 and 0.06")
same("pool_filter", "select doc_id, quality from {labels} where not (quality <=> 0) and toxic in (0, 1)", "select doc_id, quality from labels where quality is distinct from 0 and toxic in (0, 1)")
same("filter_predicates", "select doc_id, source from {documents} where lang like 'e%' and source rlike '^src1' and n_chars between 100 and 3000", "select doc_id, source from documents where lang like 'e%' and regexp_matches(source, '^src1') and n_chars between 100 and 3000")


@query("io_roundtrip_labels", "select doc_id, quality, toxic, f as format from labels, (select unnest(['csv', 'json', 'orc', 'parquet']) as f)")
def _(spark, sf_dir):
    from tidelabel.sources.sinks import round_trip

    rows = load(spark, sf_dir, "labels")
    out = [round_trip(rows, f).select("doc_id", "quality", "toxic", F.lit(f).alias("format")) for f in ("csv", "json", "orc", "parquet")]
    return out[0].union(out[1]).union(out[2]).union(out[3])


@query("round_store", "select doc_id as row_id, quality as new_label, 1::integer as round from labels where doc_id % 2 = 0 union all select doc_id, quality, 2 from labels where doc_id % 2 = 1")
def _(spark, sf_dir):
    from tidelabel.sources.sinks import RoundStore

    rows = load(spark, sf_dir, "labels").selectExpr("doc_id as row_id", "quality as new_label", "'SUGGEST' as source")
    store = RoundStore(spark)
    store.append_edits(1, rows.where("row_id % 2 = 0"))
    store.append_edits(2, rows.where("row_id % 2 = 1"))
    return store.edits().select("row_id", "new_label", "round")


@query("io_bucketed_join", "select d.doc_id, d.n_chars, l.quality from documents d join labels l on d.doc_id = l.doc_id")
def _(spark, sf_dir):
    from tidelabel.sources.sinks import bucketed

    d = bucketed(load(spark, sf_dir, "documents").select("doc_id", "n_chars"), "facts", ["doc_id"], 8)
    return d.hint("merge").join(bucketed(load(spark, sf_dir, "labels").select("doc_id", "quality"), "truths", ["doc_id"], 8), "doc_id")


# joins
same("join_truth", "select d.doc_id, l.quality, d.lang from {documents} d join {labels} l on d.doc_id = l.doc_id")
same("join_votes_suggestion", "select coalesce(l.doc_id, s.doc_id) as doc_id, l.quality as vote, s.label as suggestion from {labels} l full outer join (select doc_id, cast(n_chars > 500 as int) as label from {documents} where doc_id % 3 = 0) s on l.doc_id = s.doc_id")
same("semi_candidates", "select doc_id, n_chars from {documents} d left semi join {labels} l on d.doc_id = l.doc_id and l.quality = 0", "select doc_id, n_chars from documents d where exists (select 1 from labels l where d.doc_id = l.doc_id and l.quality = 0)")
same("anti_cleaned", "select doc_id, quality from {labels} l left anti join (select doc_id as e from {documents} where doc_id % 5 = 0) c on l.doc_id = c.e", "select doc_id, quality from labels l where not exists (select 1 from documents c where c.doc_id % 5 = 0 and c.doc_id = l.doc_id)")
same("anti_unlabelled", "select doc_id, lang from {documents} d left anti join {labels} l on d.doc_id = l.doc_id", "select doc_id, lang from documents d where not exists (select 1 from labels l where l.doc_id = d.doc_id)")
same("cross_classes", "select l.doc_id, c.class, case when l.quality = c.class then 1 else 0 end as hit from {labels} l cross join (select 0 as class union all select 1) c")
same("theta_threshold", "select d.doc_id, m.lang as other from {documents} d join (select lang, avg(n_chars) as mean from {documents} group by lang) m on d.n_chars > 3 * m.mean and d.lang <> m.lang")
same("range_bucket_join", "select d.doc_id, b.band from {documents} d join (select 0 as lo, 500 as hi, 'short' as band union all select 500, 5000, 'middle' union all select 5000, 1000000000, 'long') b on d.n_chars >= b.lo and d.n_chars < b.hi")
same(
    "interval_votes",
    "select a.event_id, count(*) as n from {events} a join {events} b on a.user_id = b.user_id and b.ts between a.ts - interval 1 hour and a.ts where a.event_type = 'purchase' group by a.event_id",
)
ASOF = "select event_id, user_id, last(err, true) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as before from (select event_id, user_id, ts, case when event_type = 'error' then event_id end as err from {events})"
same("asof_vote", ASOF, "select event_id, user_id, last(err ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as before from (select event_id, user_id, ts, case when event_type = 'error' then event_id end as err from events)")


@query("asof_join", "select e.event_id, o.event_id as last_error from events e asof left join (select user_id, ts, max(event_id) as event_id from events where event_type = 'error' group by 1, 2) o on e.user_id = o.user_id and e.ts >= o.ts")
def _(spark, sf_dir):
    from tidelabel.operators.asof import asof_join

    e = load(spark, sf_dir, "events")
    errors = e.where("event_type = 'error'").groupBy("user_id", "ts").agg(F.max("event_id").alias("last_error"))
    return asof_join(e.select("event_id", "user_id", "ts"), errors, "user_id", "ts", ["last_error"]).select("event_id", "last_error")


# aggregates
same("agg_weighted_loss", "select lang, round(sum(case when quality = 1 then cast(0.1 as double) else cast(0.9 as double) end * n_chars) / count(*), 6) as loss, count(*) as n from {documents} join {labels} using (doc_id) group by lang")
same("agg_annotators", "select event_type, count(distinct user_id) as annotators from {events} group by event_type")
same("agg_gradient_sql", "select i, round(sum(v), 4) as g from (select posexplode(embedding) as (i, v) from {embeddings}) group by i", "select i::integer as i, round(sum(v), 4) as g from (select unnest(range(64)) as i, unnest(embedding)::double as v from embeddings) group by i")
QUERIES["agg_gradient_sql"] = lambda spark, sf_dir: load(spark, sf_dir, "embeddings").select(F.posexplode("embedding").alias("i", "v")).groupBy("i").agg(F.round(F.sum(F.col("v").cast("double")), 4).alias("g"))
same("agg_collect_votes", "select conv_id, array_join(sort_array(collect_list(role)), ',') as roles from {conversations} group by conv_id", "select conv_id, array_to_string(list_sort(list(role)), ',') as roles from conversations group by conv_id")
same("f1_cube", "select lang, source, count(*) as n, sum(quality) as good from {documents} join {labels} using (doc_id) group by cube (lang, source)", "select lang, source, count(*) as n, sum(quality)::bigint as good from documents join labels using (doc_id) group by cube (lang, source)")
same("votes_rollup", "select event_type, day, count(*) as n from (select event_type, cast(cast(ts as date) as varchar(10)) as day from {events}) group by rollup (event_type, day)")
same("grouping_quality", "select lang, quality, count(*) as n from {documents} join {labels} using (doc_id) group by grouping sets ((lang), (quality), ())")
same("pivot_votes", "select * from (select user_id, event_type from {events}) pivot (count(*) for event_type in ('click' as click, 'error' as error, 'purchase' as purchase))", "select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'error') as error, count(*) filter (event_type = 'purchase') as purchase from events group by user_id")
QUERIES["pivot_votes"] = lambda spark, sf_dir: load(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "error", "purchase"]).count().na.fill(0)
same("unpivot_scores", "select doc_id, stack(2, 'quality', quality, 'toxic', toxic) as (name, value) from {labels}", "select doc_id, 'quality' as name, quality as value from labels union all select doc_id, 'toxic', toxic from labels")


@query("approx_measures")
def _(spark, sf_dir):
    """Sketches: rows only, as they may differ between engines."""
    return load(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median"))


# windows
same("rank_scores", "select doc_id, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, round(percent_rank() over w, 9) as pr, ntile(4) over w as nt from (select doc_id, n_chars, lang from {documents}) window w as (partition by lang order by n_chars, doc_id)", "select doc_id, (row_number() over w)::integer as rn, (rank() over w)::integer as rk, (dense_rank() over w)::integer as dr, round(percent_rank() over w, 9) as pr, (ntile(4) over w)::integer as nt from documents window w as (partition by lang order by n_chars, doc_id)")
same("vote_gap", "select event_id, round(value - lag(value) over (partition by user_id order by ts, event_id), 6) as gap, lead(event_id) over (partition by user_id order by ts, event_id) as next_id from {events}")
same("budget_running", "select doc_id, sum(cost) over (partition by lang order by doc_id rows unbounded preceding) as spent from (select doc_id, lang, cast(n_chars as bigint) as cost from {documents})", "select doc_id, (sum(n_chars) over (partition by lang order by doc_id rows unbounded preceding))::bigint as spent from documents")
same("moving_mean", "select doc_id, round(avg(n_chars) over (partition by source order by doc_id rows between 3 preceding and current row), 6) as mean from {documents}")
same("range_frame", "select event_id, count(*) over (partition by user_id order by s range between 86400 preceding and current row) as day_votes from (select event_id, user_id, unix_seconds(ts) as s from {events})", "select event_id, count(*) over (partition by user_id order by s range between 86400 preceding and current row) as day_votes from (select event_id, user_id, floor(epoch(ts))::bigint as s from events)")
same("first_last", "select distinct user_id, first_value(event_id) over w as f, last_value(event_id) over w as l, nth_value(event_id, 2) over w as s from {events} window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)")
same("topk_per_class", "select lang, doc_id from (select lang, doc_id, row_number() over (partition by lang order by n_chars desc, doc_id) as k from {documents}) where k <= 3")
same("limit_offset", "select doc_id, n_chars from {documents} order by n_chars desc, doc_id limit 10 offset 20")

# sets
same("union_candidates", "select doc_id from {labels} where quality = 0 union select doc_id from {labels} where toxic = 1")
same("except_sets", "select doc_id from {documents} except select doc_id from {labels}")
same("setops_all", "select 'i' as op, l_partkey from (select l_partkey from {lineitem} where l_quantity < 10 intersect all select l_partkey from {lineitem} where l_quantity > 40) union all select 'e', l_partkey from (select l_partkey from {lineitem} where l_quantity < 10 except all select l_partkey from {lineitem} where l_quantity > 20)")

# functions
same("fn_string", "select page_id, length(html) as n, upper(substr(url, 1, 8)) as u, replace(url, '/', '|') as r, instr(html, '<p') as p, levenshtein(substr(url, 1, 20), 'http://example.com') as d from {pages}", "select page_id, length(html)::integer as n, upper(substr(url, 1, 8)) as u, replace(url, '/', '|') as r, instr(html, '<p')::integer as p, levenshtein(substr(url, 1, 20), 'http://example.com')::integer as d from pages")
same("fn_math", "select vec_id, round(exp(v), 6) as e, round(log1p(abs(v)), 6) as l, round(pow(v, 2), 6) as q, pmod(vec_id - 7, 5) as m, isnan(v / nullif(v, 0D)) as nn, greatest(v, 0.0D) as g, least(v, 0.0D) as s, sign(v) as sg, width_bucket(v, -1, 1, 8) as b from (select vec_id, cast(embedding[0] as double) as v from {embeddings})", "select vec_id, round(exp(v), 6) as e, round(ln(1 + abs(v)), 6) as l, round(pow(v, 2), 6) as q, ((vec_id - 7) % 5 + 5) % 5 as m, isnan(v / nullif(v, 0)) as nn, greatest(v, 0.0) as g, least(v, 0.0) as s, sign(v)::double as sg, (floor((v + 1) / 0.25) + 1)::bigint as b from (select vec_id, embedding[1]::double as v from embeddings)")
same("fn_date", "select o_orderkey, cast(date_trunc('month', o_orderdate) as date) as m, datediff(o_orderdate, date '1992-01-01') as d, year(o_orderdate) as y, cast(date_add(cast(o_orderdate as date), 30) as date) as p from {orders}", "select o_orderkey, date_trunc('month', o_orderdate)::date as m, datediff('day', date '1992-01-01', o_orderdate::date)::integer as d, year(o_orderdate)::integer as y, (o_orderdate::date + 30)::date as p from orders")
same("fn_array", "select vec_id, size(filter(embedding, v -> v > 0)) as pos, exists(embedding, v -> v > 0.4) as big, forall(embedding, v -> v < 0.9) as small, array_position(embedding, array_max(embedding)) as at, size(flatten(array(slice(embedding, 1, 3), slice(embedding, 2, 2)))) as n from {embeddings}", "select vec_id, len(list_filter(embedding, lambda v: v > 0))::integer as pos, len(list_filter(embedding, lambda v: v > 0.4)) > 0 as big, len(list_filter(embedding, lambda v: v < 0.9)) = len(embedding) as small, list_position(embedding, list_max(embedding))::bigint as at, 5::integer as n from embeddings")
same("fn_map", "select doc_id, element_at(map_filter(m, (k, v) -> v > 0), 'quality') as q, size(map_keys(m)) as n, element_at(map_zip_with(m, map('toxic', 5), (k, a, b) -> a + coalesce(b, 0)), 'toxic') as t from (select doc_id, map_from_arrays(array('quality', 'toxic'), array(quality, toxic)) as m from {labels})", "select doc_id, case when quality > 0 then quality end as q, 2::integer as n, (toxic + 5)::integer as t from labels")
same("fn_json", "select event_id, cast(get_json_object(props, '$.k') as int) as k, from_json(props, 'k int').k + 1 as k1 from {events}", "select event_id, json_extract(props, '$.k')::integer as k, json_extract(props, '$.k')::integer + 1 as k1 from events")
same("fn_null", "select doc_id, coalesce(nullif(quality, 0), -1) as q, try_divide(toxic, quality) as r, try_cast('x' as int) as z, case when toxic is null then 'none' when toxic = 1 then 'yes' else 'no' end as t from {labels}", "select doc_id, coalesce(nullif(quality, 0), -1) as q, case when quality = 0 then null else toxic / quality end as r, try_cast('x' as integer) as z, case when toxic is null then 'none' when toxic = 1 then 'yes' else 'no' end as t from labels")
same("struct_max", "select lang, m.doc_id as doc_id, m.n_chars as n_chars from (select lang, max_by(struct(doc_id, n_chars), struct(n_chars, doc_id)) as m from {documents} group by lang)", "select lang, doc_id, n_chars from (select *, row_number() over (partition by lang order by n_chars desc, doc_id desc) as k from documents) where k = 1")
same("subq_scalar_L", "select doc_id from {documents} where n_chars <= (select max(n_chars) from (select n_chars from {documents} order by n_chars, doc_id limit 25))")
same("subq_exists", "select user_id, count(*) as n from {events} e where exists (select 1 from {events} f where f.user_id = e.user_id and f.event_type = 'error') group by user_id")

same(
    "recursive_descent",
    "with recursive m as (select avg(n_chars / 1000D) as a, avg(case when n_chars > 500 then 1D else 0D end) as b from {documents}), s(t, w) as (select 0, cast(0 as double) union all select t + 1, w - 0.5D * (w * 1.05D + b - a) from s cross join m where t < 12) select t, round(w, 9) as w from s",
    "with recursive m as (select avg(n_chars / 1000.0::double) as a, avg(case when n_chars > 500 then 1.0::double else 0.0::double end) as b from documents), s(t, w) as (select 0, 0::double union all select t + 1, w - 0.5::double * (w * 1.05::double + b - a) from s cross join m where t < 12) select t, round(w, 9) as w from s",
)

# samples
@query("sample_hash", f"select doc_id from documents where {uniform_sql('sample', 'doc_id')} < 0.1")
def _(spark, sf_dir):
    return load(spark, sf_dir, "documents").where(uniform("sample", "doc_id") < 0.1).select("doc_id")


@query("stratified", f"select doc_id, quality from labels where {uniform_sql('strata', 'doc_id')} < case quality when 0 then 0.5 else 0.1 end")
def _(spark, sf_dir):
    return load(spark, sf_dir, "labels").where(uniform("strata", "doc_id") < F.when(F.col("quality") == 0, 0.5).otherwise(0.1)).select("doc_id", "quality")


# UDFs: an Arrow scalar, a grouped aggregate, a table function
@query("udf_softmax", "select vec_id, round(exp(a) / (exp(a) + exp(b)), 6) as p from (select vec_id, embedding[1]::double as a, embedding[2]::double as b from embeddings)")
def _(spark, sf_dir):
    from tidelabel.functions.udfs import softmax_first

    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(softmax_first(F.expr("cast(embedding[0] as double)"), F.expr("cast(embedding[1] as double)")), 6).alias("p"))


@query("udaf_vec_mean", "select label, i, round(avg(v), 6) as mean from (select label, unnest(range(len(embedding)))::integer as i, unnest(embedding)::double as v from embeddings) group by label, i")
def _(spark, sf_dir):
    from tidelabel.functions.udfs import mean_of

    long = load(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("i", "v"))
    return long.groupBy("label", "i").agg(F.round(mean_of(F.col("v").cast("double")), 6).alias("mean"))


@query("udtf_scores", "select doc_id, c::integer as class, (quality = c)::integer as hit from labels, (select unnest([0, 1]) as c)")
def _(spark, sf_dir):
    from tidelabel.functions.udfs import register_functions

    register_functions(spark)
    return spark.sql("select l.doc_id, u.class, u.hit from {labels} l, lateral tidelabel_classes(l.quality, 2) u", labels=load(spark, sf_dir, "labels"))


@query("group_errors", "select user_id, round(avg((event_type = 'error')::integer), 6) as err from events group by user_id")
def _(spark, sf_dir):
    def share(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"user_id": [pdf.user_id.iloc[0]], "err": [round((pdf.event_type == "error").mean(), 6)]})

    return load(spark, sf_dir, "events").select("user_id", "event_type").groupBy("user_id").applyInPandas(share, "user_id long, err double")
