"""Queries of features, weak labels, models and influence scores with their DuckDB twins."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from tidelabel.functions.features import STATISTICS, labelling_votes, combined_votes, standardised_sql, text_statistics, text_statistics_sql, vector_features, vector_features_sql
from tidelabel.functions.linear import argmax, argmin, cross_entropy, dot, fixed_model, list_sql, logits, logits_sql, softmax, softmax_sql, total, uplift
from tidelabel.functions.rand import random_weak, random_weak_sql, split_of, split_sql
from tidelabel.operators import baselines, influence, pruner
from tidelabel.operators.pruner import drift
from tidelabel.sources.tables import load

C, D, GAMMA = 4, 65, 0.8
W, V = fixed_model(C, D, 3, 60.0), fixed_model(C, D, 5, 10.0)
#: A model near W, standing for an earlier round.
W0 = W + fixed_model(C, D, 2, 4000.0)
#: Weights of the binary model over the eight text statistics and 1.0.
W_DOC = np.array([[0.0] * 9, [0.3, -1.1, 0.4, 0.2, -0.7, 0.1, 0.9, 0.5, 1.2]])

QUERIES, ORACLES = {}, {}


def query(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return add


# features and weak labels
@query("feat_documents", f"select doc_id, {', '.join(f'round({s}, 9) as {s}' for s in STATISTICS)} from (select doc_id, {text_statistics_sql()} from documents)")
def _(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id", *text_statistics()).select("doc_id", *(F.round(s, 9).alias(s) for s in STATISTICS))


@query("feat_vec_norm", "select vec_id, round(list_inner_product(list_transform(embedding, lambda e: e::double), list_transform(embedding, lambda e: e::double)), 6) as norm2 from embeddings")
def _(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(total(F.transform("embedding", lambda e: e.cast("double") * e.cast("double"))), 6).alias("norm2"))


LF_SQL = f"""(select doc_id, case when digits < 0.01 then 1 else 0 end as lf_digits, case when log_size > 5 then 1 else 0 end as lf_length,
 case when others < 0.1 then 1 else 0 end as lf_symbols, case when distinct_lines > 0.8 then 1 else 0 end as lf_lines from (select doc_id, {text_statistics_sql()} from documents))"""


@query("lf_votes", f"select *, lf_digits + lf_length + lf_symbols + lf_lines as n_pos, 4 - (lf_digits + lf_length + lf_symbols + lf_lines) as n_neg from {LF_SQL}")
def _(spark, sf_dir):
    rows = load(spark, sf_dir, "documents").select("doc_id", *text_statistics()).select("doc_id", *labelling_votes())
    n = sum(F.col(c) for c in ("lf_digits", "lf_length", "lf_symbols", "lf_lines"))
    return rows.withColumn("n_pos", n).withColumn("n_neg", F.lit(4) - n)


@query("weak_labels", f"""select doc_id, round(1 - p, 9) as p0, round(p, 9) as p1 from (select doc_id, least(greatest(1 / (1 + exp(-(
 (2 * lf_digits - 1) * ln(0.83 / (1 - 0.83)) + (2 * lf_length - 1) * ln(0.83 / (1 - 0.83)) + (2 * lf_symbols - 1) * ln(0.82 / (1 - 0.82)) + (2 * lf_lines - 1) * ln(0.88 / (1 - 0.88))))), 0.05), 0.95) as p from {LF_SQL})""")
def _(spark, sf_dir):
    rows = load(spark, sf_dir, "documents").select("doc_id", *text_statistics()).select("doc_id", *labelling_votes()).select("doc_id", combined_votes().alias("p"))
    return rows.selectExpr("doc_id", "round(p[0], 9) as p0", "round(p[1], 9) as p1")


@query("random_weak", f"select vec_id, unnest(range(4))::integer as class, round(unnest({random_weak_sql('weak', 'vec_id', C)}), 9) as p from embeddings")
def _(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode(random_weak("weak", "vec_id", C)).alias("class", "p")).withColumn("p", F.round("p", 9))


@query("harden", f"select vec_id, (list_position(weak, list_max(weak)) - 1)::integer as hard from (select vec_id, {random_weak_sql('weak', 'vec_id', C)} as weak from embeddings)")
def _(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("vec_id", argmax(random_weak("weak", "vec_id", C)).alias("hard"))


@query("split_counts", f"select {split_sql('doc_id')} as split, quality, count(*) as n from documents join labels using (doc_id) group by 1, 2")
def _(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels"), "doc_id").groupBy(split_of("doc_id").alias("split"), "quality").agg(F.count("*").alias("n"))


# scores over vectors with fixed models
def vectors(spark, sf_dir):
    rows = load(spark, sf_dir, "embeddings").select("vec_id", vector_features().alias("x"), random_weak("weak", "vec_id", C).alias("y"))
    return rows.select("vec_id", "x", "y", softmax(logits(F.col("x"), W)).alias("p"), softmax(logits(F.col("x"), W0)).alias("q"), logits(F.col("x"), V).alias("s"))


def engine_rows(spark, sf_dir):
    """The same rows as the engine reads them."""
    rows = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), vector_features().alias("x"), random_weak("weak", "vec_id", C).alias("weak"))
    return rows.withColumn("truth", argmax(logits(F.col("x"), fixed_model(4, 65, 5, 1.0)))).withColumn("is_clean", F.lit(False)).withColumn("split", F.lit("train"))


def engine_long(scores):
    return influence.scores_long(scores).select(F.col("row_id").alias("vec_id"), "class", F.round("score", 6).alias("score"))


def engine_top(scores, *extra, n=20):
    best = influence.select_top(scores, n)
    return best.select(F.expr("cast(row_number() over (order by best_score, row_id) as int)").alias("rank"), F.col("row_id").alias("vec_id"), *extra)


BASE = f"""(select vec_id, x, y, z, {softmax_sql('z')} as p, {softmax_sql('z0')} as q, s from (select *, {logits_sql('x', W)} as z, {logits_sql('x', W0)} as z0, {logits_sql('x', V)} as s
 from (select vec_id, {vector_features_sql()} as x, {random_weak_sql('weak', 'vec_id', C)} as y from embeddings)))"""
DOT = "list_inner_product"


def uplift_sql(gamma: float, p: str = "p") -> str:
    return f"list_transform(s, lambda v: {DOT}(y, s) + {1 - gamma!r} * ({DOT}({p}, s) - {DOT}(y, s)) - v)"


def long_sql(scores: str) -> str:
    return f"select vec_id, unnest(range({C}))::integer as class, round(unnest(scores), 6) as score from (select vec_id, {scores} as scores from {BASE})"


def long(rows, scores):
    return rows.select("vec_id", F.posexplode(scores).alias("class", "score")).withColumn("score", F.round("score", 6))


@query("softmax_scores", f"select vec_id, {', '.join(f'round(p[{c + 1}], 6) as p{c}' for c in range(C))} from {BASE}")
def _(spark, sf_dir):
    return vectors(spark, sf_dir).selectExpr("vec_id", *(f"round(p[{c}], 6) as p{c}" for c in range(C)))


@query("uplift_scores", long_sql(uplift_sql(GAMMA)))
def _(spark, sf_dir):
    return engine_long(influence.uplift_influence(engine_rows(spark, sf_dir), W, V, GAMMA))


@query("uplift_gamma1", long_sql(uplift_sql(1.0)))
def _(spark, sf_dir):
    return engine_long(influence.uplift_influence(engine_rows(spark, sf_dir), W, V, 1.0))


@query("reweight_scores", f"select vec_id, round({1 - GAMMA!r} * ({DOT}(p, s) - {DOT}(y, s)), 6) as score from {BASE}")
def _(spark, sf_dir):
    found = influence.scored(engine_rows(spark, sf_dir), lambda x, y: influence.reweight_scores(x, y, W, V, GAMMA))
    return found.select(F.col("row_id").alias("vec_id"), F.round("best_score", 6).alias("score"))


@query("deletion_scores", f"select vec_id, round({DOT}(p, s) - {DOT}(y, s), 6) as score, round(-{GAMMA!r} * ({DOT}(p, s) - {DOT}(y, s)), 6) as effect from {BASE}")
def _(spark, sf_dir):
    rows = engine_rows(spark, sf_dir)
    one = lambda convention, name: influence.deletion_influence(rows, W, V, GAMMA, convention).select(F.col("row_id").alias("vec_id"), F.round("best_score", 6).alias(name))
    return one("printed", "score").join(one("effect", "effect"), "vec_id")


@query("deletion_one_test_row", f"""with b as (select * from {BASE}), t as (select x as tx, list_transform(range(1, {C + 1}), lambda c: p[c] - (case when c = 1 then 1 else 0 end)) as g from b where vec_id = (select min(vec_id) from b))
select vec_id, round(-{DOT}(list_transform(range(1, {C + 1}), lambda c: p[c] - y[c]), g) * {DOT}(x, tx) * 0.01, 6) + 0.0 as score from b, t""")
def _(spark, sf_dir):
    # against one trusted row of class 0, with the identity for the Hessian: v is -gradient, scaled
    rows = vectors(spark, sf_dir)
    one = rows.orderBy("vec_id").limit(1).select(F.col("x").alias("tx"), F.transform("p", lambda p, i: p - (i == 0).cast("double")).alias("g"))
    r = F.zip_with("p", "y", lambda a, b: a - b)
    return rows.crossJoin(F.broadcast(one)).select("vec_id", (F.round(-dot(r, F.col("g")) * dot(F.col("x"), F.col("tx")) * F.lit(0.01), 6) + F.lit(0.0)).alias("score"))


@query("feature_scores", f"""select vec_id, round(sqrt({DOT}(f, f)), 6) as norm from (select vec_id, list_transform(range(1, {D + 1}), lambda j: {' + '.join(f'(p[{c + 1}] - y[{c + 1}]) * ({list_sql(V[c])})[j] + p[{c + 1}] * (s[{c + 1}] - ps) * ({list_sql(W[c])})[j]' for c in range(C))}) as f from (select *, {DOT}(p, s) as ps from {BASE}))""")
def _(spark, sf_dir):
    from tidelabel.operators.influence import feature_scores, scored

    rows = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), vector_features().alias("x"), random_weak("weak", "vec_id", C).alias("weak"))
    f = scored(rows, lambda x, y: feature_scores(x, y, W, V))
    return f.select(F.col("row_id").alias("vec_id"), F.round(F.sqrt(total(F.transform("scores", lambda v: v * v))), 6).alias("norm"))


@query("label_gradient_scores", long_sql(f"list_transform(s, lambda v: {DOT}(p, s) - v)"))
def _(spark, sf_dir):
    return engine_long(influence.label_gradient_influence(engine_rows(spark, sf_dir), W, V))


@query("suggested_labels", f"select vec_id, (list_position(u, list_min(u)) - 1)::integer as best_class from (select vec_id, {uplift_sql(GAMMA)} as u from {BASE})")
def _(spark, sf_dir):
    return influence.uplift_influence(engine_rows(spark, sf_dir), W, V, GAMMA).select(F.col("row_id").alias("vec_id"), "best_class")


def top_sql(score: str, extra: str = "") -> str:
    return f"select row_number() over (order by score, vec_id)::integer as rank, vec_id{extra} from (select *, {score} as score from (select *, {uplift_sql(GAMMA)} as u from {BASE})) order by score, vec_id limit 20"


@query("topb_uplift", top_sql("list_min(u)", ", (list_position(u, list_min(u)) - 1)::integer as best_class"))
def _(spark, sf_dir):
    return engine_top(influence.uplift_influence(engine_rows(spark, sf_dir), W, V, GAMMA), "best_class")


@query("sign_report", f"select list_min(u) < 0 as is_harmful, count(*) as n from (select {uplift_sql(GAMMA)} as u from {BASE}) group by 1")
def _(spark, sf_dir):
    return influence.sign_report(influence.uplift_influence(engine_rows(spark, sf_dir), W, V, GAMMA))


@query("least_confidence", top_sql("list_max(p)"))
def _(spark, sf_dir):
    return engine_top(baselines.least_confidence(engine_rows(spark, sf_dir), W))


@query("entropy_rank", top_sql(f"{DOT}(p, list_transform(p, lambda a: ln(a)))"))
def _(spark, sf_dir):
    return engine_top(baselines.entropy(engine_rows(spark, sf_dir), W))


@query("margin_rank", top_sql("list_reverse_sort(p)[1] - list_reverse_sort(p)[2]"))
def _(spark, sf_dir):
    return engine_top(baselines.margin(engine_rows(spark, sf_dir), W))


@query("random_rank", top_sql("('0x' || md5('random|' || vec_id::varchar)[1:8])::bigint"))
def _(spark, sf_dir):
    return engine_top(baselines.random_order(engine_rows(spark, sf_dir)))


@query("overlap_rankers", f"""with u as (select *, {uplift_sql(GAMMA)} as u from {BASE}), a as (select vec_id from u order by list_min(u), vec_id limit 50), b as (select vec_id from u order by list_max(p), vec_id limit 50),
 c as (select vec_id from u order by {DOT}(p, list_transform(p, lambda a: ln(a))), vec_id limit 50)
select 'uplift, confidence' as pair, count(*) as n_common from (select * from a intersect select * from b) union all select 'uplift, entropy', count(*) from (select * from a intersect select * from c) union all select 'confidence, entropy', count(*) from (select * from b intersect select * from c)""")
def _(spark, sf_dir):
    rows = vectors(spark, sf_dir)
    best = {
        "uplift": rows.withColumn("k", F.array_min(uplift(F.col("s"), F.col("p"), F.col("y"), GAMMA))), "confidence": rows.withColumn("k", F.array_max("p")),
        "entropy": rows.withColumn("k", total(F.transform("p", lambda a: a * F.log(a)))),
    }
    best = {n: r.orderBy("k", "vec_id").limit(50).select("vec_id") for n, r in best.items()}
    pairs = (("uplift", "confidence"), ("uplift", "entropy"), ("confidence", "entropy"))
    out = [best[a].intersect(best[b]).agg(F.count("*").alias("n_common")).select(F.lit(f"{a}, {b}").alias("pair"), "n_common") for a, b in pairs]
    return out[0].union(out[1]).union(out[2])


# brackets at fixed models: W0 is the anchor, W the current one
GAP = drift(V, W, W0)


def bounds_sql(kind: str) -> str:
    h = f"({DOT}(x, x) / 2)"
    centre = uplift_sql(GAMMA, "q")
    wide = {"softmax_exact": "0.0", "half": "0.5", "printed": "1.0"}[kind]
    moved = f"({DOT}(y, list_transform(y, lambda e: 1.0)) - y[i] + 1 - y[i])"
    radius = f"({h} * {GAP.size!r} * ({(1 - GAMMA) / 2!r} + {wide} * {moved}))"
    return f"select vec_id, i, c[i] as center, c[i] + {(1 - GAMMA) / 2 * GAP.along!r} * {h} - {radius} as lower, c[i] + {(1 - GAMMA) / 2 * GAP.along!r} * {h} + {radius} as upper, e[i] as exact from (select *, {centre} as c, {uplift_sql(GAMMA)} as e from {BASE}), (select unnest(range(1, {C + 1})) as i)"


def bounds(spark, sf_dir, kind="softmax_exact"):
    """The engine's brackets, with W0 as anchor and the Hessian norms' ceiling."""
    return pruner.brackets(pruner.provenance(engine_rows(spark, sf_dir), W0, V), V, W, W0, GAMMA, kind, "ceiling")


def ends(found):
    return found.select(F.col("row_id").alias("vec_id"), F.posexplode(F.arrays_zip("lower", "upper")).alias("class", "z")).select("vec_id", "class", F.round("z.lower", 6).alias("lower"), F.round("z.upper", 6).alias("upper"))


for _kind, _name in (("printed", "brackets_printed"), ("half", "brackets_half"), ("softmax_exact", "brackets_exact")):
    ORACLES[_name] = f"select vec_id, (i - 1)::integer as class, round(lower, 6) as lower, round(upper, 6) as upper from ({bounds_sql(_kind)})"
    QUERIES[_name] = lambda spark, sf_dir, kind=_kind: ends(bounds(spark, sf_dir, kind))


@query("bracket_violations", " union all ".join(f"select '{k}' as kind, count(*) filter (exact < lower - 1e-9 or exact > upper + 1e-9) as violations from ({bounds_sql(k)})" for k in ("printed", "half", "softmax_exact")))
def _(spark, sf_dir):
    rows = engine_rows(spark, sf_dir).persist()
    exact = influence.uplift_influence(rows, W, V, GAMMA)
    found = [(kind, pruner.violations(bounds(spark, sf_dir, kind), exact)) for kind in ("printed", "half", "softmax_exact")]
    rows.unpersist()
    return spark.createDataFrame(found, "kind string, violations long")


PER_ROW = f"(select vec_id, min(center) as center, arg_min(upper, center) as upper, min(upper) as least_upper, min(lower) as lower, arg_min(i, exact) - 1 as best_class, min(exact) as exact from ({bounds_sql('softmax_exact')}) group by vec_id)"
PRINTED = f"with r as {PER_ROW}, t as (select max(upper) as l from (select upper from r order by center, vec_id limit 10)), k as (select r.* from r, t where lower <= l) "
TIGHT = f"with r as {PER_ROW}, t as (select max(least_upper) as l from (select least_upper from r order by least_upper, vec_id limit 10)), k as (select r.* from r, t where lower <= l) "


@query("candidates", PRINTED + "select vec_id from k")
def _(spark, sf_dir):
    return pruner.candidates(bounds(spark, sf_dir), 10).withColumnRenamed("row_id", "vec_id")


@query("candidates_tight", TIGHT + "select vec_id from k")
def _(spark, sf_dir):
    return pruner.candidates(bounds(spark, sf_dir), 10, "tight").withColumnRenamed("row_id", "vec_id")


@query("candidate_count", PRINTED + "select (select count(*) from k) as n, (select count(*) from r) as n_total")
def _(spark, sf_dir):
    b = bounds(spark, sf_dir)
    return pruner.candidates(b, 10).agg(F.count("*").alias("n")).crossJoin(b.agg(F.count("*").alias("n_total")))


def pruned(spark, sf_dir):
    return pruner.pruned_top(bounds(spark, sf_dir), W, V, GAMMA, 10)[0]


@query("pruned_topb", PRINTED + "select row_number() over (order by exact, vec_id)::integer as rank, vec_id, best_class::integer as best_class from k order by exact, vec_id limit 10")
def _(spark, sf_dir):
    return engine_top(pruned(spark, sf_dir), "best_class", n=10)


@query("pruned_equals_full", PRINTED + f""", a as (select vec_id from (select vec_id, list_min({uplift_sql(GAMMA)}) as u from {BASE}) order by u, vec_id limit 10), b as (select vec_id from k order by exact, vec_id limit 10)
select (select count(*) from (select * from a except select * from b)) as only_a, (select count(*) from (select * from b except select * from a)) as only_b""")
def _(spark, sf_dir):
    from tidelabel.operators.measures import same_picks

    return same_picks(influence.select_top(influence.uplift_influence(engine_rows(spark, sf_dir), W, V, GAMMA), 10), pruned(spark, sf_dir))


@query("hessian_norm_power")
def _(spark, sf_dir):
    return pruner.provenance(engine_rows(spark, sf_dir), W, V).select(F.col("row_id").alias("vec_id"), F.round("h", 6).alias("h"))


# the binary model over documents
DOC = f"(select doc_id, text, x, 1 / (1 + exp(-list_inner_product(x, {list_sql(W_DOC[1])}))) as p from (select doc_id, text, {standardised_sql()} as x from (select doc_id, text, {text_statistics_sql()} from documents)))"


def doc_model(spark, sf_dir):
    from tidelabel.functions.features import with_text_features

    rows = with_text_features(load(spark, sf_dir, "documents").select("doc_id", "text"))
    return rows.withColumn("p", F.expr("1D") / (F.lit(1.0) + F.exp(-dot(F.col("x"), W_DOC[1]))))


@query("sigmoid_scores", f"select doc_id, round(p, 6) as p from {DOC}")
def _(spark, sf_dir):
    return doc_model(spark, sf_dir).select("doc_id", F.round("p", 6).alias("p"))


@query("hessian_norm_binary", f"select doc_id, round(2 * p * (1 - p) * list_inner_product(x, x), 6) as h from {DOC}")
def _(spark, sf_dir):
    return doc_model(spark, sf_dir).select("doc_id", F.round(F.lit(2.0) * F.col("p") * (F.lit(1.0) - F.col("p")) * dot(F.col("x"), F.col("x")), 6).alias("h"))


@query("confusion_matrix", f"select quality as truth, (p > 0.5)::integer as pred, count(*) as n from {DOC} join labels using (doc_id) group by 1, 2")
def _(spark, sf_dir):
    from tidelabel.operators.measures import confusion

    return confusion(doc_model(spark, sf_dir).join(load(spark, sf_dir, "labels"), "doc_id").select(F.col("quality").alias("truth"), (F.col("p") > 0.5).cast("int").alias("pred")))


@query("f1_score", f"select round(2.0 * count(*) filter (quality = 1 and p > 0.5) / greatest(count(*) filter (quality = 1) + count(*) filter (p > 0.5), 1), 9) as f1 from {DOC} join labels using (doc_id)")
def _(spark, sf_dir):
    from tidelabel.operators.measures import f1_frame

    rows = doc_model(spark, sf_dir).join(load(spark, sf_dir, "labels"), "doc_id").select(F.col("quality").alias("truth"), (F.col("p") > 0.5).cast("int").alias("pred"))
    return f1_frame(rows).select(F.round("f1", 9).alias("f1"))


@query("f1_macro", """with t as (select case role when 'user' then 0 when 'assistant' then 1 else 2 end as truth, case when length(text) < 160 then 2 when length(text) < 500 then 0 else 1 end as pred from conversations),
c as (select unnest([0, 1, 2]) as c) select round(avg(f), 9) as f1 from (select 2.0 * count(*) filter (truth = c and pred = c) / greatest(count(*) filter (truth = c) + count(*) filter (pred = c), 1) as f from t, c group by c)""")
def _(spark, sf_dir):
    from tidelabel.operators.measures import f1_frame

    rows = load(spark, sf_dir, "conversations").selectExpr("case role when 'user' then 0 when 'assistant' then 1 else 2 end as truth", "case when length(text) < 160 then 2 when length(text) < 500 then 0 else 1 end as pred")
    return f1_frame(rows, macro=True).select(F.round("f1", 9).alias("f1"))


@query("agreement", f"select count(*) filter (best_class = truth) as n_match, count(*) as n from (select (list_position(u, list_min(u)) - 1) as best_class, (list_position(t, list_max(t)) - 1) as truth from (select vec_id, {uplift_sql(GAMMA)} as u, {logits_sql('x', fixed_model(4, 65, 5, 1.0))} as t from {BASE}) order by list_min(u), vec_id limit 20)")
def _(spark, sf_dir):
    from tidelabel.operators.measures import agreement

    rows = engine_rows(spark, sf_dir)
    return agreement(influence.select_top(influence.uplift_influence(rows, W, V, GAMMA), 20), rows)


@query("nn_cosine", """with e as (select vec_id, list_transform(embedding, lambda v: v::double) as x from embeddings), t as (select * from e),
n as (select e.vec_id, t.vec_id as nn_id, list_inner_product(e.x, t.x) / sqrt(list_inner_product(e.x, e.x) * list_inner_product(t.x, t.x)) as c from e join t on e.vec_id <> t.vec_id where e.vec_id % 50 = 0)
select vec_id, nn_id, rank from (select vec_id, nn_id, row_number() over (partition by vec_id order by round(c, 9) desc, nn_id)::integer as rank from n) where rank <= 5""")
def _(spark, sf_dir):
    from tidelabel.operators.neighbours import nearest_trusted

    rows = load(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    return nearest_trusted(rows.where("vec_id % 50 = 0"), rows, 5)
