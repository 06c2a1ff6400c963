"""Declared schemas: the given tables and the relations of the engine."""

from __future__ import annotations

# Columns of the given tables.
TABLES = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "conversations": "conv_id long, turn long, role string, text string",
}

ACTION = "struct<action_type:string,target_obj:string,receptacle_obj:string>"
#: One trajectory a row: task, trajectory, its +1/-1 label, its steps in order.
PACKED = f"task long, traj long, r int, steps array<struct<action:{ACTION},text:string>>"
#: One step a row, with keys of its prefix tree node and of the parent.
STEPS = f"task long, traj long, r int, n_steps int, t int, parent_key long, node_key long, action {ACTION}, text string"
CANDIDATES = "sample_id long, task string, cand_no int, answer double, truth double"
TASK_RATE = "task string, iter int, sampled long, effective long, eta double, eta_ema double, quota long"
EVENTS_STREAM = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
TIMING = "stage string, method string, phase string, seconds double"
SCORES = "system string, benchmark string, category string, value double"
