"""Queries of training, gradients, solvers, annotation and refresh with their DuckDB twins.

The model is binary over three text statistics and 1.0, so that SQL can follow every step.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from tidelabel.config import CleanConfig
from tidelabel.functions.features import CENTRE, SPREAD, STATISTICS, standardised_sql, text_statistics, text_statistics_sql
from tidelabel.functions.rand import random_weak, random_weak_sql, split_of, split_sql, uniform_sql
from tidelabel.operators import annotate
from tidelabel.operators.core import LocalRows, conjugate_gradient, gradient, hessian, hvp, rows_of, train_sgd, trusted_rows, validation_gradient
from tidelabel.operators.replay import CurvatureMemory
from tidelabel.sources.tables import labelled_documents, load, training_set

QUERIES, ORACLES = {}, {}
USED = ("letters", "others", "distinct_words")
CFG = CleanConfig(lam=0.05, rate=0.5)
#: Weights of class 1; class 0 has their negative.
U = np.array([0.4, -0.3, 0.5, 0.6])
STEPS = 4


def query(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return add


def small_train(spark, sf_dir):
    rows = labelled_documents(spark, sf_dir).selectExpr("doc_id as row_id", "text", "quality as truth").select("row_id", "truth", *text_statistics())
    x = F.array(*((F.col(s) - m) / d for s, m, d in zip(STATISTICS, CENTRE, SPREAD) if s in USED), F.lit(1.0))
    return training_set(rows.withColumn("x", x), 2)


def both(u):
    return np.array([-u, u])


ROWS = f"""rows as materialized (select doc_id, x, quality as truth, ({random_weak_sql('weak', 'doc_id', 2)})[2] as y, {split_sql('doc_id')} as split
 from (select doc_id, quality, {standardised_sql(USED)} as x from (select doc_id, quality, {text_statistics_sql()} from documents join labels using (doc_id)))),
tr as materialized (select * from rows where split = 'train'), va as materialized (select * from rows where split = 'val')"""


def margin(u) -> str:
    return f"(1 / (1 + exp(-2 * list_inner_product(x, {[float(a) for a in u]}))))"


def from_vector(spark, v, names=("j", "g"), digits=9):
    return spark.createDataFrame([(j, round(float(a), digits)) for j, a in enumerate(v)], f"{names[0]} int, {names[1]} double")


@query("weighted_loss", f"with {ROWS} select round(sum(0.8 * -(y * ln(p) + (1 - y) * ln(1 - p))) / count(*), 9) as loss, count(*) as n, round(0.8 * count(*), 9) as weight_sum from (select *, {margin(U)} as p from tr)")
def _(spark, sf_dir):
    from tidelabel.functions.linear import cross_entropy, literal, logits, softmax

    rows = small_train(spark, sf_dir).where("split = 'train'").withColumn("p", softmax(logits(F.col("x"), both(U))))
    weight = F.when(F.col("is_clean"), 1.0).otherwise(CFG.gamma)
    return rows.agg(F.round(F.sum(weight * cross_entropy(F.col("p"), F.col("weak"))) / F.count("*"), 9).alias("loss"), F.count("*").alias("n"), F.round(F.sum(weight), 9).alias("weight_sum"))


BATCH = "((doc_id * 7919) % 1000003) % 4"


@query("batch_gradient", f"with {ROWS} select batch_id, j, round(avg(0.8 * (p - y) * xj), 9) as g from (select {BATCH} as batch_id, unnest(range(4))::integer as j, unnest(x) as xj, p, y from (select *, {margin(U)} as p from tr)) group by 1, 2")
def _(spark, sf_dir):
    from tidelabel.functions.linear import logits, softmax

    rows = small_train(spark, sf_dir).where("split = 'train'").withColumn("p", softmax(logits(F.col("x"), both(U))))
    long = rows.select(F.pmod(F.pmod(F.col("row_id") * 7919, F.lit(1000003)), F.lit(4)).alias("batch_id"), (F.lit(CFG.gamma) * (F.expr("p[1]") - F.expr("weak[1]"))).alias("r"), F.posexplode("x").alias("j", "xj"))
    return long.groupBy("batch_id", "j").agg(F.round(F.avg(F.col("r") * F.col("xj")), 9).alias("g"))


@query("val_gradient", f"with {ROWS} select j, round(avg((p - truth) * xj), 9) as g from (select unnest(range(4))::integer as j, unnest(x) as xj, p, truth from (select *, {margin(U)} as p from va)) group by 1")
def _(spark, sf_dir):
    return from_vector(spark, validation_gradient(trusted_rows(small_train(spark, sf_dir), "val", CFG), both(U))[1])


@query("hvp", f"with {ROWS} select j, round(sum(0.8 * p * (1 - p) * 2 * list_inner_product(x, [1.0, 2.0, -1.0, 0.5]) * xj) / any_value(n) + 0.05 * any_value(([1.0, 2.0, -1.0, 0.5])[j + 1]), 9) as hv from (select unnest(range(4))::integer as j, unnest(x) as xj, x, p, n from (select *, {margin(U)} as p, count(*) over () as n from tr)) group by 1")
def _(spark, sf_dir):
    rows = rows_of(small_train(spark, sf_dir), CFG)
    return from_vector(spark, hvp(rows, both(U), both(np.array([1.0, 2.0, -1.0, 0.5])), CFG.lam)[1], ("j", "hv"))


HESS = f"select a.j as i, b.j as j, sum(0.8 * a.p * (1 - a.p) * a.xj * b.xj) / any_value(a.n) as h from e a join e b using (doc_id) group by 1, 2"
EXPLODED = f"e as (select doc_id, unnest(range(4))::integer as j, unnest(x) as xj, p, n from (select *, {margin(U)} as p, count(*) over () as n from tr))"


@query("hessian_small", f"with {ROWS}, {EXPLODED} select i, j, round(h + case when i = j then 0.05 else 0 end, 9) as h from ({HESS})")
def _(spark, sf_dir):
    h = hessian(rows_of(small_train(spark, sf_dir), CFG), both(U), CFG.lam)[4:, 4:]
    return spark.createDataFrame([(i, j, round(float(h[i, j]), 9)) for i in range(4) for j in range(4)], "i int, j int, h double")


def descent_sql() -> str:
    """Unrolled steps of full-batch descent from zero."""
    parts = ["w0 as (select [0.0, 0.0, 0.0, 0.0] as w)"]
    for t in range(STEPS):
        parts.append(f"w{t + 1} as materialized (select list(w - 0.5 * (g + 0.05 * w) order by j) as w from (select j, avg(0.8 * (1 / (1 + exp(-2 * list_inner_product(x, w))) - y) * x[j]) as g, any_value(w[j]) as w from tr, w{t}, (select unnest(range(1, 5)) as j) group by j))")
    return ", ".join(parts)


@query("gd_recursive", f"with {ROWS}, {descent_sql()} " + " union all ".join(f"select {t}::integer as t, (unnest(range(4)))::integer as j, round(unnest(w), 9) as w from w{t}" for t in range(STEPS + 1)))
def _(spark, sf_dir):
    rows = rows_of(small_train(spark, sf_dir), CFG)
    _, trace = train_sgd(rows, CFG, STEPS + 1)
    return spark.createDataFrame([(t, j, round(float(a), 9) + 0.0) for t, s in enumerate(trace) for j, a in enumerate(s.w[1])], "t int, j int, w double")


@query("cg_solve_small", f"""with {ROWS}, {EXPLODED}, m as (select i, j, 2 * h + case when i = j then 0.05 else 0 end as h from ({HESS})), g as (select j, avg((p - truth) * xj) as b from (select unnest(range(4))::integer as j, unnest(x) as xj, p, truth from (select *, {margin(U)} as p from va)) group by 1),
hl as materialized (select list(h order by i, j) as h from m), bl as materialized (select list(b order by j) as b from g)""" + "".join(
    # conjugate gradients, four turns for four unknowns, unrolled; state: v, r, p as lists
    (", s0 as (select h, [0.0, 0.0, 0.0, 0.0] as v, b as r, b as p from hl, bl)" if t == 0 else "") +
    f", a{t} as materialized (select *, list_inner_product(r, r) as rr, list_transform(range(4), lambda i: list_inner_product(h[4 * i + 1:4 * i + 4], p)) as ap from s{t})"
    f", s{t + 1} as materialized (select h, v, r, list_transform(range(1, 5), lambda i: r[i] + case when rr = 0 then 0 else list_inner_product(r, r) / rr end * p[i]) as p from (select h, p, rr, list_transform(range(1, 5), lambda i: v[i] + k * p[i]) as v, list_transform(range(1, 5), lambda i: r[i] - k * ap[i]) as r from (select *, case when rr = 0 then 0 else rr / list_inner_product(p, ap) end as k from a{t})))"
    for t in range(4)) + " select (unnest(range(4)))::integer as j, round(-unnest(v), 6) as v from s4")
def _(spark, sf_dir):
    train = small_train(spark, sf_dir)
    rows, w = rows_of(train, CFG), both(U)
    b = validation_gradient(trusted_rows(train, "val", CFG), w)
    v = -conjugate_gradient(lambda u: hvp(rows, w, u, CFG.lam), b, most=20)
    return from_vector(spark, v[1], ("j", "v"), 6)


SGD_STEPS, SGD_BATCHES = 12, 4


def sgd_sql() -> str:
    """Unrolled mini-batch steps; an empty batch has the penalty's gradient."""
    parts = ["w0 as (select [0.0, 0.0, 0.0, 0.0] as w)"]
    for t in range(SGD_STEPS):
        epoch, number = divmod(t, SGD_BATCHES)
        inside = f"((doc_id * 7919 + {epoch * 104729}) % 1000003) % {SGD_BATCHES} = {number}"
        parts.append(f"g{t} as materialized (select j, any_value(w[j]) as w, coalesce(avg(0.8 * (1 / (1 + exp(-2 * list_inner_product(x, w))) - y) * x[j]) filter ({inside}), 0) + 0.05 * any_value(w[j]) as g, count(*) filter ({inside}) as n from tr, w{t}, (select unnest(range(1, 5)) as j) group by j)")
        parts.append(f"w{t + 1} as materialized (select list(w - 0.5 * g order by j) as w from g{t})")
    return ", ".join(parts)


# both classes' rows have the same size
@query("sgd_trace", f"with {ROWS}, {sgd_sql()} " + " union all ".join(f"select {t}::integer as t, round(sqrt(2 * sum(w * w)), 9) as norm_w, round(sqrt(2 * sum(g * g)), 9) as norm_g, any_value(n) as n_batch from g{t}" for t in range(SGD_STEPS)))
def _(spark, sf_dir):
    cfg = CFG.but(batches=SGD_BATCHES)
    _, trace = train_sgd(rows_of(small_train(spark, sf_dir), cfg), cfg, SGD_STEPS)
    return spark.createDataFrame([(t, round(float(np.linalg.norm(s.w)), 9), round(float(np.linalg.norm(s.g)), 9), s.n) for t, s in enumerate(trace)], "t int, norm_w double, norm_g double, n_batch long")


#: Steps of the kept curvature pairs, and the vector that their matrix is applied to.
PAIRS = [np.roll(np.array([1.0, 0.5, -0.25, 0.1]), k) for k in range(3)]
APPLIED = np.array([1.0, -1.0, 2.0, 0.5])


def lbfgs_sql() -> str:
    """The compact form unrolled: updates of a multiple of the identity by one pair after another, the matrix as a list."""
    vector = lambda v: str([float(a) for a in v])
    times = lambda m, v: f"list_transform(range(4), lambda i: list_inner_product({m}[4 * i + 1:4 * i + 4], {v}))"
    parts = ["hl as materialized (select list(h + case when i = j then 0.05 else 0 end order by i, j) as h from (" + HESS + "))"]
    last = vector(PAIRS[-1])
    parts.append(f"b0 as materialized (select h, list_transform(range(16), lambda k: case when k // 4 = k % 4 then list_inner_product({last}, {times('h', last)}) / list_inner_product({last}, {last}) else 0 end) as b from hl)")
    for k, step in enumerate(map(vector, PAIRS)):
        parts.append(f"p{k} as materialized (select h, b, {times('b', step)} as bs, {times('h', step)} as y from b{k})")
        parts.append(f"b{k + 1} as materialized (select h, list_transform(range(16), lambda k: b[k + 1] - bs[k // 4 + 1] * bs[k % 4 + 1] / list_inner_product({step}, bs) + y[k // 4 + 1] * y[k % 4 + 1] / list_inner_product({step}, y)) as b from p{k})")
    return ", ".join(parts) + f" select (unnest(range(4)))::integer as j, round(unnest({times('b', vector(APPLIED))}), 9) as bu from b{len(PAIRS)}"


@query("lbfgs_product", f"with {ROWS}, {EXPLODED}, {lbfgs_sql()}")
def _(spark, sf_dir):
    """The quasi-Newton matrix of pairs (step, change of the gradient by the training rows' Hessian), applied to a vector."""
    h, memory = hessian(rows_of(small_train(spark, sf_dir), CFG), both(U), CFG.lam)[4:, 4:], CurvatureMemory(len(PAIRS))
    for s in PAIRS:
        memory.add(s, h @ s)
    return from_vector(spark, memory.apply(APPLIED), ("j", "bu"))


# annotation
TRUTH = "t as (select doc_id, quality as truth from labels)"
SIM = ", ".join([TRUTH] + [f"v{a} as (select doc_id, 'human{a}' as annotator, case when {uniform_sql(f'ann{a}', 'doc_id')} < 0.05 then (truth + 1) % 2 else truth end as label from t)" for a in (1, 2, 3)] + ["v as (select * from v1 union all select * from v2 union all select * from v3)"])


def truth_rows(spark, sf_dir):
    return load(spark, sf_dir, "labels").selectExpr("doc_id as row_id", "quality as truth")


def votes(spark, sf_dir):
    return annotate.simulate_votes(truth_rows(spark, sf_dir), 3, 0.05, 2)


@query("simulate_votes", f"with {SIM} select doc_id, annotator, label::integer as label from v")
def _(spark, sf_dir):
    return votes(spark, sf_dir).withColumnRenamed("row_id", "doc_id")


@query("majority_vote", f"with {SIM} select doc_id, label::integer as label, n as votes from (select doc_id, label, count(*) as n, row_number() over (partition by doc_id order by count(*) desc, label) as k from v group by 1, 2) where k = 1")
def _(spark, sf_dir):
    return annotate.majority_vote(votes(spark, sf_dir)).withColumnRenamed("row_id", "doc_id")


#: Suggestions for the annotation queries: the truth, but wrong where the id is divisible by 4.
SUGGESTED = "case when doc_id % 4 = 0 then 1 - truth else truth end"


def clean(spark, sf_dir, strategy):
    truth = truth_rows(spark, sf_dir)
    picks = truth.selectExpr("row_id", "cast(case when row_id % 4 = 0 then 1 - truth else truth end as int) as best_class")
    return annotate.clean_labels(picks, strategy, truth, 2).withColumnRenamed("row_id", "doc_id")


def majority_sql(source: str) -> str:
    return f"select doc_id, (sum(label) * 2 > count(*))::integer as new_label from ({source}) group by 1"


for _name, _strategy, _sql in (
    ("clean_human3", "HUMAN3", f"with {SIM} {majority_sql('select * from v')}"),
    ("clean_suggest", "SUGGEST", f"with {SIM} select doc_id, ({SUGGESTED})::integer as new_label from t"),
    ("clean_mix", "MIX", f"with {SIM} {majority_sql(f'select * from v1 union all select * from v2 union all select doc_id, chr(115), {SUGGESTED} from t')}"),
):
    QUERIES[_name], ORACLES[_name] = (lambda spark, sf_dir, s=_strategy: clean(spark, sf_dir, s)), _sql


@query("annotation_cost", "select strategy, (each * n)::integer as votes from (values ('HUMAN3', 3), ('SUGGEST', 0), ('MIX', 2)) c(strategy, each), (select count(*) as n from labels where quality = 0)")
def _(spark, sf_dir):
    n = load(spark, sf_dir, "labels").where("quality = 0").count()
    return spark.createDataFrame([(s, annotate.annotation_cost(s, n)) for s in annotate.VOTES], "strategy string, votes int")


@query("annotator_error", f"with {SIM} select annotator, round(avg((label <> truth)::integer), 9) as err, count(*) as n from v join t using (doc_id) group by 1")
def _(spark, sf_dir):
    return annotate.annotator_errors(votes(spark, sf_dir), truth_rows(spark, sf_dir)).withColumn("err", F.round("err", 9))


@query("apply_edits", f"with {ROWS} select doc_id, round(case when doc_id % 5 = 0 then truth::double else y end, 9) as p1, case when doc_id % 5 = 0 then 1.0 else 0.8 end::double as weight from rows")
def _(spark, sf_dir):
    train = small_train(spark, sf_dir)
    edits = train.where("row_id % 5 = 0").selectExpr("row_id", "truth as new_label")
    rows = annotate.apply_edits(train, edits, 2)
    return rows.select(F.col("row_id").alias("doc_id"), F.round(F.expr("weak[1]"), 9).alias("p1"), F.when(F.col("is_clean"), 1.0).otherwise(CFG.gamma).alias("weight"))


# refresh: the batch gradient's identity
def parts(spark, sf_dir):
    train = small_train(spark, sf_dir)
    rows = rows_of(train, CFG)
    m = rows.ids % 5 == 0
    truth = {r.row_id: r.truth for r in train.select("row_id", "truth").collect()}
    new = np.eye(2)[[truth[i] for i in rows.ids[m]]]
    return rows, m, new


GRAD = "select j, sum((case when {w}) * (p - {y}) * x[j]) / sum({c}) as g from tr_p, (select unnest(range(1, 5)) as j) where {k} group by j"
TRP = f"tr_p as (select *, {margin(U)} as p from tr)"


@query("label_edit_gradient", f"with {ROWS}, {TRP} select (j - 1)::integer as j, round(avg(case when doc_id % 5 = 0 then p - truth else 0.8 * (p - y) end * x[j]), 9) as g from tr_p, (select unnest(range(1, 5)) as j) group by j")
def _(spark, sf_dir):
    from tidelabel.operators.core import gradient_of

    rows, m, new = parts(spark, sf_dir)
    w = both(U)
    whole, n = rows.total(lambda x, y, g: gradient_of(x, y, g, w))
    fix = gradient_of(rows.x[m], new, np.ones(m.sum()), w) - gradient_of(rows.x[m], rows.y[m], np.full(m.sum(), CFG.gamma), w)
    return from_vector(spark, ((whole + fix) / n)[1])


@query("delete_add_gradient", f"with {ROWS}, {TRP} select (j - 1)::integer as j, round(avg(0.8 * (p - y) * x[j]) filter (doc_id % 5 <> 0), 9) as g_identity, round(avg(0.8 * (p - y) * x[j]) filter (doc_id % 5 <> 0), 9) as g_direct from tr_p, (select unnest(range(1, 5)) as j) group by j")
def _(spark, sf_dir):
    from tidelabel.operators.core import gradient_of

    rows, m, _ = parts(spark, sf_dir)
    w = both(U)
    whole, n = rows.total(lambda x, y, g: gradient_of(x, y, g, w))
    removed = gradient_of(rows.x[m], rows.y[m], np.full(m.sum(), CFG.gamma), w)
    kept = LocalRows(rows.ids[~m], rows.x[~m], rows.y[~m], rows.clean[~m], CFG.gamma)
    direct, k = gradient(kept, w, 0.0)
    identity = (whole - removed) / (n - m.sum())
    return spark.createDataFrame([(j, round(float(identity[1][j]), 9), round(float(direct[1][j]), 9)) for j in range(4)], "j int, g_identity double, g_direct double")
