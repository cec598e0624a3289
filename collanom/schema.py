"""Fixed schemas of the tables that the engine passes around."""

from __future__ import annotations

SERIES_LONG = "series_id string, t bigint, component int, x double"
TYPICAL = "series_id string, component int, mu double, sigma double, n_obs bigint, degenerate boolean"
CANDIDATE = "series_id string, s bigint, e bigint, k int, score double, kind string"
AFFECTED = "array<struct<component:int,saving:double,estimate:double,start_lag:int,end_lag:int>>"
TRUTH = "series_id string, k int, s bigint, e bigint, component int, d int, f int, mu double"

#: Physical schemas of the given tables; declared, never inferred.
TABLES = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
}
