"""Declared schemas of the tables and of the shapes that the engine passes around."""

from __future__ import annotations

from pyspark.sql import types as T


_KINDS = {"INT": T.IntegerType(), "BIGINT": T.LongType(), "DOUBLE": T.DoubleType(), "FLOAT": T.FloatType(), "STRING": T.StringType(), "TIMESTAMP": T.TimestampType()}


def _of(columns: str) -> T.StructType:
    """A schema from ``name TYPE, ...``; needs no session, so modules import without one."""

    def kind(name: str) -> T.DataType:
        return T.ArrayType(kind(name[6:-1])) if name.startswith("ARRAY<") else _KINDS[name]

    return T.StructType([T.StructField(n, kind(k)) for n, k in (c.split() for c in columns.split(","))])


TABLES: dict[str, T.StructType] = {
    "region": _of("r_regionkey INT, r_name STRING"),
    "nation": _of("n_nationkey INT, n_name STRING, n_regionkey INT"),
    "customer": _of("c_custkey BIGINT, c_name STRING, c_nationkey INT, c_acctbal DOUBLE, c_mktsegment STRING"),
    "supplier": _of("s_suppkey BIGINT, s_name STRING, s_nationkey INT, s_acctbal DOUBLE"),
    "part": _of("p_partkey BIGINT, p_name STRING, p_brand STRING, p_type STRING, p_size INT, p_retailprice DOUBLE"),
    "orders": _of("o_orderkey BIGINT, o_custkey BIGINT, o_orderstatus STRING, o_totalprice DOUBLE, o_orderdate TIMESTAMP, o_orderpriority STRING"),
    "lineitem": _of(
        "l_orderkey BIGINT, l_partkey BIGINT, l_suppkey BIGINT, l_linenumber INT, l_quantity DOUBLE, l_extendedprice DOUBLE, "
        "l_discount DOUBLE, l_tax DOUBLE, l_returnflag STRING, l_linestatus STRING, l_shipdate TIMESTAMP"
    ),
    "events": _of("event_id BIGINT, ts TIMESTAMP, user_id BIGINT, event_type STRING, value DOUBLE, props STRING"),
    "documents": _of("doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT"),
    "embeddings": _of("vec_id BIGINT, embedding ARRAY<FLOAT>, label INT"),
    "pages": _of("page_id BIGINT, url STRING, html STRING"),
    "benchmark": _of("item_id BIGINT, text STRING"),
    "labels": _of("doc_id BIGINT, quality INT, toxic INT"),
    "conversations": _of("conv_id BIGINT, turn BIGINT, role STRING, text STRING"),
}

#: Examples as the trainers read them: one row each, ids ascending.
PACKED = _of("example_id BIGINT, batch_id BIGINT, label DOUBLE, idx ARRAY<BIGINT>, val ARRAY<DOUBLE>")
CELLS = _of("class INT, row INT, bucket INT, value DOUBLE")
TOPK = _of("class INT, rank INT, feature_id BIGINT, estimate DOUBLE")
LOG = _of(
    "step BIGINT, loss DOUBLE, grad_norm DOUBLE, pairs_kept INT, active BIGINT, heap_churn INT, cells_used BIGINT, "
    "pair_values BIGINT, stale DOUBLE"
)
#: What a trainer's task returns: blocks of the parts of a model.
BLOCKS = _of("kind STRING, config BIGINT, class INT, row INT, start BIGINT, ids ARRAY<BIGINT>, vals ARRAY<DOUBLE>")
SWEEP = _of(
    "workload STRING, method STRING, mode STRING, cf DOUBLE, k INT, eta DOUBLE, tau INT, seed BIGINT, metric STRING, value DOUBLE, seconds DOUBLE"
)
