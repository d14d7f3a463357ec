"""Fixed schemas; tables are read with them, never inferred at run time."""

from __future__ import annotations

#: Columns of the given tables.
TABLES = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "events": "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
}
TRAIN = "row_id bigint, x array<double>, weak array<double>, truth int, is_clean boolean, split string"
EDITS = "round int, row_id bigint, new_label int, source string"
SCORES = "row_id bigint, best_class int, best_score double, scores array<double>"
MODEL = "name string, value array<double>"
TRACE = "t int, w array<double>, g array<double>, n_batch bigint"
ROUNDS = "round int, n_cleaned int, n_candidates bigint, n_pool bigint, val_loss double, val_f1 double, test_f1 double, agreed int, votes int, t_inf double, t_grad double, t_update double"
