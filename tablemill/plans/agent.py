"""Queries of the agent runtime."""

from __future__ import annotations

from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.operators import agent as A
from tablemill.operators import metrics as M
from tablemill.plans.registry import query

ASKED = [
    ("q1", "What is the average total price of orders?", "orders"), ("q2", "How many customers are in each market segment?", "customer"), ("q3", "What is the largest retail price of a part?", "part"),
    ("q4", "What is the mean discount of line items?", "lineitem"), ("q5", "Which supplier has the highest account balance?", "supplier"), ("q6", "How many events of each event type happened?", "events"),
]


def asked(t):
    return t.spark.createDataFrame([(a, b) for a, b, _ in ASKED], "query_id string, query string")


def schema_docs(t):
    """Descriptions of all tables and columns with the values they hold."""
    return A.value_docs(t.spark, lambda name: getattr(t, name))


@query("agt_embed_search")
def agt_embed_search(t):
    return A.embed_search(asked(t), schema_docs(t))


@query("agt_rerank")
def agt_rerank(t):
    docs = schema_docs(t)
    return A.rerank(A.embed_search(asked(t), docs), asked(t), docs)


@query("agt_retrieval_recall")
def agt_retrieval_recall(t):
    """Recall of the right table at five, without and with the second stage, against the whole schema; and the words each hands on."""
    docs = schema_docs(t)
    first = A.embed_search(asked(t), docs)
    gold = t.spark.createDataFrame([(a, c) for a, _, c in ASKED], "query_id string, item string")

    def measured(name, ranked):
        items = ranked.join(docs, "item_id")
        best = items.groupBy("query_id", F.col("table_id").alias("item")).agg(F.min("rank").alias("rank"))
        return M.recall_at(best, gold, 5).select(F.lit(name).alias("way"), "queries", "recall", "mrr").crossJoin(items.agg(F.sum(F.size(A.words(F.col("text")))).alias("words")))

    whole = asked(t).crossJoin(docs).select("query_id", "item_id", F.lit(1).alias("rank"))
    out = measured("first_stage", first.where("rank <= 5"))
    return out.unionByName(measured("reranked", A.rerank(first, asked(t), docs))).unionByName(measured("whole_schema", whole))


@query("agt_schema_retrieval")
def agt_schema_retrieval(t):
    docs = schema_docs(t)
    return A.schema_of(A.rerank(A.embed_search(asked(t), docs), asked(t), docs), docs, t.spark)


CHUNK_SQL = r"""w AS (SELECT doc_id, regexp_extract_all(text, '\S+') AS ws FROM documents), s AS (SELECT doc_id, ws, unnest(range(greatest(0, ceil((len(ws) - 40) / 160.0)::INT - 1) + 1)) AS pos FROM w WHERE len(ws) > 0),
ch AS (SELECT doc_id, pos::INT AS pos, array_to_string(ws[pos * 160 + 1 : pos * 160 + 200], ' ') AS text FROM s)"""


@query("agt_chunks", f"WITH {CHUNK_SQL} SELECT doc_id, pos, md5(text) AS h FROM ch")
def agt_chunks(t):
    return A.chunks(t.documents).select("doc_id", "pos", F.md5("text").alias("h"))


def _g3(c):
    return f"CASE WHEN len({c}) >= 3 THEN list_distinct(list_transform(range(1, len({c}) - 1), lambda i: array_to_string({c}[i:i+2], ' '))) ELSE [] END"


@query("agt_knowledge", f"""WITH {CHUNK_SQL}, q AS (SELECT item_id AS query_id, unnest({_g3("b")}) AS g FROM (SELECT item_id, regexp_extract_all(lower(text), '\\S+') AS b FROM benchmark)),
c AS (SELECT doc_id, pos, unnest({_g3("b")}) AS g FROM (SELECT doc_id, pos, regexp_extract_all(lower(text), '\\S+') AS b FROM ch)), h AS (SELECT query_id, doc_id, pos, count(*)::BIGINT AS hits FROM c JOIN q USING (g) GROUP BY 1, 2, 3)
SELECT query_id, doc_id, pos, hits, rank::INT AS rank FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, doc_id, pos) AS rank FROM h) WHERE rank <= 3""")
def agt_knowledge(t):
    """Fragments for every test passage."""
    return A.knowledge(t.benchmark.select(F.col("item_id").alias("query_id"), F.col("text").alias("query")), t.documents)


@query("agt_context_budget", r"""WITH r AS (SELECT source AS query_id, doc_id AS item_id, text, row_number() OVER (PARTITION BY source ORDER BY doc_id) AS rank FROM documents), u AS (SELECT *, sum(len(regexp_extract_all(text, '\S+'))) OVER (PARTITION BY query_id ORDER BY rank ROWS UNBOUNDED PRECEDING)::BIGINT AS used FROM r) SELECT query_id, item_id, used FROM u WHERE used <= 2000""")
def agt_context_budget(t):
    return A.within_budget(t.documents.select(F.col("source").alias("query_id"), F.col("doc_id").alias("item_id"), "text"), 2000, "item_id")


@query("agt_refuse", f"SELECT conv_id, turn, regexp_matches(lower(text), '{A.OFF_TOPIC}') AS refused FROM conversations WHERE role = 'user'")
def agt_refuse(t):
    return t.conversations.where("role = 'user'").select("conv_id", "turn", A.refuse(F.col("text")).alias("refused"))


@query("agt_loop")
def agt_loop(t):
    """The retry loop on six questions: vague column names fail once and are repaired from the error."""
    out = None
    for qid, text, table in ASKED:
        one = A.loop(t.spark, (qid, text), {table: getattr(t, table)})
        out = one if out is None else out.unionByName(one)
    return out


@query("agt_one_shot_contrast")
def agt_one_shot_contrast(t):
    """Share of questions answered with one round and with up to three."""
    runs = agt_loop(t).cache()
    one = runs.where("round = 1").agg(F.lit(1).alias("max_rounds"), F.round(F.avg((F.col("status") == "ok").cast("int")), 6).alias("answered"))
    many = runs.groupBy("query_id").agg(F.max((F.col("status") == "ok").cast("int")).alias("ok")).agg(F.lit(3).alias("max_rounds"), F.round(F.avg("ok"), 6).alias("answered"))
    return one.unionByName(many)


@query("agt_chart_facts", """WITH s AS (SELECT event_type AS name, date_diff('day', DATE '2024-01-01', ts::DATE)::INT AS x, round(sum(value), 2) AS y FROM events GROUP BY 1, 2), m AS (SELECT name, avg(y) AS m, stddev_samp(y) AS s FROM s GROUP BY 1)
SELECT name, round(regr_slope(y, x), 6) AS slope, arg_max(x, y) AS top_x, max(y) AS top_y, (count(*) FILTER (WHERE abs(y - m) > 2 * m.s))::BIGINT AS n_outliers FROM s JOIN m USING (name) GROUP BY name""")
def agt_chart_facts(t):
    s = t.events.groupBy(F.col("event_type").alias("name"), F.datediff("ts", F.lit("2024-01-01").cast("date")).alias("x")).agg(F.round(F.sum("value"), 2).alias("y"))
    return A.chart_facts(s)


EXPIRE_SQL = """WITH g AS (SELECT user_id AS session, ts, coalesce(ts >= lag(ts) OVER w + INTERVAL 6 HOURS, TRUE)::INT AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), r AS (SELECT *, sum(new) OVER (PARTITION BY session ORDER BY ts) AS run FROM g)
SELECT session, min(ts) AS started, max(ts) AS last_activity, max(ts) + INTERVAL 6 HOURS AS expires_at FROM r GROUP BY session, run"""


@query("agt_sandbox_expiry", EXPIRE_SQL)
def agt_sandbox_expiry(t):
    return A.expire(t.events.select(F.col("user_id").alias("session"), "ts"))


@query("agt_report", f"""WITH r AS (SELECT o_orderpriority AS class, CASE WHEN {det.sql_unit("'st'", 'o_orderkey')} < 0.8 THEN 'ok' ELSE 'error' END AS status, 1 + {det.sql_pick(3, "'ro'", 'o_orderkey')} AS rounds FROM orders) SELECT class, count(*)::BIGINT AS runs, round(avg((status = 'ok')::INT), 6) AS success, round(avg(rounds), 6) AS rounds FROM r GROUP BY CUBE (class)""")
def agt_report(t):
    k = F.col("o_orderkey")
    return A.report(t.orders.select(F.col("o_orderpriority").alias("class"), F.when(det.unit("st", k) < 0.8, "ok").otherwise("error").alias("status"), (1 + det.pick(3, "ro", k)).alias("rounds")))


@query("agt_dsl", "SELECT o_orderpriority, count(*)::BIGINT AS n, round(avg(o_totalprice * 1.1), 4) AS mean FROM orders WHERE o_totalprice > 100000 GROUP BY 1")
def agt_dsl(t):
    text = "from orders | keep o_totalprice > 100000 | with taxed = o_totalprice * 1.1D | group o_orderpriority : n = count(*) & mean = round(avg(taxed), 4) | show o_orderpriority, n, mean"
    return A.Dsl.compile(text, lambda name: getattr(t, name))


@query("agt_dag", "WITH d AS (SELECT event_type, ts::DATE AS day, avg(value) AS v FROM events GROUP BY 1, 2), f AS (SELECT event_type, avg(v) AS m FROM d GROUP BY 1) SELECT event_type, strftime(day, '%Y-%m-%d') AS day, round(v, 8) AS value, CASE WHEN v > m THEN 'above' ELSE 'below' END AS note FROM d JOIN f USING (event_type)")
def agt_dag(t):
    """Intent, analysis and note as three steps."""
    daily = lambda: t.events.groupBy("event_type", F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.avg("value").alias("v"))
    steps = {"read": daily, "mean": lambda d: d.groupBy("event_type").agg(F.avg("v").alias("m")), "note": lambda d, m: d.join(F.broadcast(m), "event_type").select("event_type", "day", F.round("v", 8).alias("value"), F.when(F.col("v") > F.col("m"), "above").otherwise("below").alias("note"))}
    return A.Dag(steps, [("read", "mean"), ("read", "note"), ("mean", "note")]).run()["note"]


TOOL_CALLS = [
    ("count", '{"tool": "query", "arguments": {"sql": "SELECT r_name FROM region"}}'), ("write", '{"tool": "query", "arguments": {"sql": "DROP TABLE region"}}'),
    ("columns", '{"tool": "describe", "arguments": {"table": "part"}}'), ("nothing", '{"tool": "describe", "arguments": {"table": "nope"}}'),
    ("bars", '{"tool": "plot", "arguments": {"table": "part", "kind": "bar", "x": "p_brand", "y": "p_retailprice"}}'), ("cake", '{"tool": "plot", "arguments": {"table": "part", "kind": "cake", "x": "p_brand", "y": "p_size"}}'),
    ("mail", '{"tool": "mail", "arguments": {}}'), ("broken", '{"tool": '),
]


@query("agt_tools", "SELECT 'count' AS call_id, 'query' AS tool, 'ok' AS status, count(*)::BIGINT AS rows FROM region UNION ALL SELECT * FROM (VALUES ('write', 'query', 'error', 0), ('columns', 'describe', 'ok', 6), ('nothing', 'describe', 'error', 0), ('bars', 'plot', 'ok', 0), ('cake', 'plot', 'error', 0), ('mail', 'mail', 'unknown_tool', 0), ('broken', '', 'unreadable', 0))")
def agt_tools(t):
    """Calls of tools as a model would write them, right and wrong."""
    return A.dispatch(t.spark, TOOL_CALLS, {"region": t.region})
