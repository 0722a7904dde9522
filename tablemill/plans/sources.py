"""Queries of sources, sinks, user functions and plan checks."""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import functions as F

from tablemill.operators import encoder as E
from tablemill.operators import factory as X
from tablemill.operators import tables as T
from tablemill.plans import tables as table_plans
from tablemill.plans.registry import query
from tablemill.sources import files, grids
from tablemill.streaming.windows import scratch

CUSTOMER_SQL = "SELECT c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment FROM customer"

for _fmt, _options in (("csv", {"header": "true"}), ("json", {}), ("orc", {}), ("xml", {"rowTag": "row"})):

    @query(f"src_{_fmt}_roundtrip", CUSTOMER_SQL)
    def src_roundtrip(t, fmt=_fmt, options=_options):
        return files.round_trip(t.customer, fmt, **options)


@query("src_text_lines", "SELECT count(*)::BIGINT AS n FROM customer")
def src_text_lines(t):
    return files.sample_lines(t.customer).agg(F.count("*").alias("n"))


@query("src_html_grid", table_plans.GRID_SQL + "SELECT 'revenue#0' AS table_id, r::INT AS r, c::INT AS c, rowspan, colspan, value, is_header FROM grid")
def src_html_grid(t):
    """A merged-header table written as markup and read again by its spans."""
    return grids.from_html(grids.to_html(table_plans.grid(t)), "table_id", "html")


@query("src_grid_datasource")
def src_grid_datasource(t):
    """Inline irregular tables through the Python data source, then flattened."""
    t.spark.dataSource.register(grids.GridSource)
    text = json.dumps({"plan": [[{"v": "item", "rs": 2, "h": True}, {"v": "2024", "cs": 2, "h": True}, None], [None, {"v": "q1", "h": True}, {"v": "q2", "h": True}], ["a", "1", "2"], ["b", "3", "4"]]})
    return T.flatten_headers(T.unmerge(t.spark.read.format("grid").option("grids", text).load()))


@query("sink_jsonl_samples")
def sink_jsonl_samples(t):
    return files.sample_lines(X.prompts(X.questions(t.spark))).agg(F.count("*").alias("lines"), F.count_if(F.col("value").startswith("{")).alias("objects"))


@query("sink_partitioned_rounds", "SELECT round, count(*)::BIGINT AS n FROM (SELECT CASE WHEN o_orderkey % 3 = 1 THEN 1 ELSE 2 END AS round FROM orders WHERE o_orderkey % 3 > 0) GROUP BY 1")
def sink_partitioned_rounds(t):
    """Two rounds; the second is written twice and replaces only itself."""
    path = scratch(t.spark, "rounds")
    rows = t.orders.select("o_orderkey", (F.col("o_orderkey") % 3).cast("int").alias("round")).where("round > 0")
    files.save_round(rows, path)
    files.save_round(rows.where("round = 2"), path)
    return t.spark.read.parquet(path).groupBy("round").agg(F.count("*").alias("n"))


@query("sink_bucketed_join", "SELECT c_mktsegment, count(*)::BIGINT AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def sink_bucketed_join(t):
    """Both sides bucketed on the key: the join needs no exchange of its own."""
    import uuid

    a, b = (f"tm_bucket_{uuid.uuid4().hex}" for _ in range(2))
    t.orders.select("o_custkey").write.bucketBy(8, "o_custkey").saveAsTable(a)
    t.customer.select("c_custkey", "c_mktsegment").write.bucketBy(8, "c_custkey").saveAsTable(b)
    return t.spark.table(a).join(t.spark.table(b), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("udtf_grid_cells", table_plans.GRID_SQL + "SELECT table_id, r::INT AS r, c::INT AS c, value FROM uc")
def udtf_grid_cells(t):
    """Spans spread by a table function beside the native form."""

    class Spread:
        def eval(self, table_id: str, r: int, c: int, rowspan: int, colspan: int, value: str):
            for i in range(rowspan):
                for j in range(colspan):
                    yield table_id, r + i, c + j, value

    t.spark.udtf.register("tm_spread", F.udtf(Spread, returnType="table_id string, r int, c int, value string"))
    table_plans.grid(t).createOrReplaceTempView("tm_grid")
    return t.spark.sql("SELECT s.* FROM tm_grid g, LATERAL tm_spread(g.table_id, g.r, g.c, g.rowspan, g.colspan, g.value) s")


@query("udaf_online_softmax", "SELECT event_type, round(max(value) + ln(sum(exp(value - m))), 6) AS lse FROM (SELECT event_type, value, max(value) OVER (PARTITION BY event_type) AS m FROM events) GROUP BY event_type")
def udaf_online_softmax(t):
    """Log-sum-exp by group from partial states (largest value, scaled sum) that merge in any order."""

    def partial(frames):
        states: dict = {}
        for pdf in frames:
            for k, v in pdf.groupby("event_type")["value"]:
                top = float(v.max())
                total = float(E.np.exp(v.to_numpy() - top).sum())
                if k in states:
                    old, s = states[k]
                    new = max(old, top)
                    states[k] = (new, s * E.np.exp(old - new) + total * E.np.exp(top - new))
                else:
                    states[k] = (top, total)
        yield pd.DataFrame([(k, a, b) for k, (a, b) in states.items()], columns=["event_type", "top", "total"])

    s = t.events.select("event_type", "value").mapInPandas(partial, "event_type string, top double, total double")
    top = s.groupBy("event_type").agg(F.max("top").alias("m"))
    return s.join(F.broadcast(top), "event_type").groupBy("event_type").agg(F.round(F.max("m") + F.log(F.sum(F.col("total") * F.exp(F.col("top") - F.col("m")))), 6).alias("lse"))


@query("udf_python_compile", "SELECT * FROM (VALUES ('a', TRUE), ('b', FALSE), ('c', TRUE)) v(id, compiles)")
def udf_python_compile(t):
    from tablemill.operators.samples import compile_ok

    df = t.spark.createDataFrame([("a", "x = 1"), ("b", "x = ("), ("c", "")], "id string, text string")
    return compile_ok(df).select("id", "compiles")


@query("plan_pushdown_check")
def plan_pushdown_check(t):
    """What the optimizer did for a narrow query over a wide table: filter pushed, two columns read, no product."""
    df = t.orders.where("o_totalprice > 400000").select("o_orderkey", "o_totalprice")
    plan = df._jdf.queryExecution().executedPlan().toString()
    rows = [("filter_pushed", "GreaterThan(o_totalprice" in plan), ("two_columns_read", "ReadSchema: struct<o_orderkey:bigint,o_totalprice:double>" in plan), ("no_product", "Cartesian" not in plan)]
    return t.spark.createDataFrame(rows, "check string, holds boolean")
