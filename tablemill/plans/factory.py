"""Queries of the sample factory."""

from __future__ import annotations

from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.operators import corpus as C
from tablemill.operators import factory as X
from tablemill.operators import metrics as M
from tablemill.operators.tables import inclusions  # noqa: F401  (joins of generated questions rest on it)
from tablemill.plans.registry import query


def _quote(s):
    return "NULL" if s is None else "'" + str(s).replace("'", "''") + "'"


_COLS = [(t, c, s, "number" if s in X.NUMERIC else "category" if s == "category" else "other", X.KEY_OF[t]) for t, cs in X.SEMANTIC.items() for c, s in cs.items()] + [(t, "", "table", "table", X.KEY_OF[t]) for t in X.SEMANTIC]
Q_SQL = (
    "WITH cols(table_id, col, sem, kind, key) AS (VALUES " + ", ".join("(" + ", ".join(map(_quote, r)) + ")" for r in _COLS) + "), tpl(template, class, kind, question, sql) AS (VALUES "
    + ", ".join(f"({i}, " + ", ".join(map(_quote, t)) + ")" for i, t in enumerate(X.TEMPLATES)) + "), "
    "q AS (SELECT concat_ws('-', template::VARCHAR, table_id, col) AS sample_id, table_id, col, class, replace(replace(replace(question, '{t}', table_id), '{c}', col), '{k}', key) AS query, replace(replace(replace(sql, '{t}', table_id), '{c}', col), '{k}', key) AS gold_sql FROM cols JOIN tpl USING (kind)) "
)

_D = det.sql_pick(5, "'draft'", "sample_id")
D_SQL = Q_SQL + f""", d AS (SELECT *, (['column', 'syntax', 'comment', 'language', 'none'])[d + 1] AS fault, CASE d WHEN 0 THEN replace(gold_sql, col, col || '_x') WHEN 1 THEN replace(gold_sql, 'FROM', 'FORM') WHEN 2 THEN '-- ' || gold_sql WHEN 3 THEN 'import pandas as pd' || chr(10) || 'print(1)' ELSE gold_sql END AS draft FROM (SELECT *, {_D} AS d FROM q WHERE gold_sql IS NOT NULL)) """


@query("fac_queries", Q_SQL + "SELECT * FROM q")
def fac_queries(t):
    return X.questions(t.spark)


@query("fac_queries_by_class", Q_SQL + "SELECT class, count(*)::BIGINT AS n, count(DISTINCT query)::BIGINT AS kinds FROM q GROUP BY 1")
def fac_queries_by_class(t):
    return X.questions(t.spark).groupBy("class").agg(F.count("*").alias("n"), F.countDistinct("query").alias("kinds"))


@query("fac_classify", Q_SQL + ", c AS (SELECT class, CASE " + " ".join(f"WHEN regexp_matches(lower(query), '{p}') THEN '{n}'" for n, p in X.CLASS_RULES) + " END AS pred FROM q) SELECT class, pred, count(*)::BIGINT AS n FROM c GROUP BY 1, 2")
def fac_classify(t):
    return X.questions(t.spark).select("class", X.classify(F.col("query")).alias("pred")).groupBy("class", "pred").agg(F.count("*").alias("n"))


@query("fac_clarify", Q_SQL + ", m AS (SELECT table_id, string_agg(col, ', ' ORDER BY col) AS ms FROM cols WHERE kind = 'number' GROUP BY 1) SELECT sample_id, 'Which measure do you mean: ' || coalesce(ms, 'number of rows') || '?' AS follow_up FROM q LEFT JOIN m USING (table_id) WHERE class = 'fuzzy'")
def fac_clarify(t):
    return X.clarify(X.questions(t.spark), X.columns_frame(t.spark))


@query("fac_jargon", "SELECT n_nationkey, 'extended price after discount of extended price after discount in ' || n_name AS q FROM nation")
def fac_jargon(t):
    return t.nation.select("n_nationkey", X.with_jargon(F.concat(F.lit("revenue of revenue in "), "n_name"), X.JARGON).alias("q"))


@query("fac_diverse", Q_SQL + "SELECT count(*)::BIGINT AS n, count(DISTINCT lower(query))::BIGINT AS distinct_queries FROM q")
def fac_diverse(t):
    return X.questions(t.spark).agg(F.count("*").alias("n"), F.countDistinct(F.lower("query")).alias("distinct_queries"))


@query("fac_domain", "SELECT * FROM (VALUES ('customer', 'sales'), ('supplier', 'purchasing'), ('part', 'purchasing'), ('orders', 'sales'), ('lineitem', 'sales'), ('nation', 'geography'), ('events', 'web')) v(table_id, domain)")
def fac_domain(t):
    words = {"sales": ["order", "customer", "linenumber", "discount"], "purchasing": ["supp", "brand"], "geography": ["region"], "web": ["user", "event"]}
    cols = X.columns_frame(t.spark).where("col <> ''")
    hits = [F.sum(F.col("col").rlike("|".join(ws)).cast("int") + F.col("table_id").rlike("|".join(ws)).cast("int")).alias(d) for d, ws in words.items()]
    scored = cols.groupBy("table_id").agg(*hits)
    best = F.greatest(*words)
    label = None
    for d in ("web", "purchasing", "sales", "geography"):
        label = F.when(F.col(d) == best, d) if label is None else label.when(F.col(d) == best, d)
    return scored.select("table_id", label.alias("domain"))


@query("fac_repair_pairs", D_SQL + "SELECT sample_id, 0 AS turn, draft AS code FROM d WHERE fault <> 'none' UNION ALL SELECT sample_id, 1, gold_sql FROM d WHERE fault <> 'none'")
def fac_repair_pairs(t):
    return X.repair_pairs(X.drafts(X.questions(t.spark)))


CHAIN_SQL = f"""WITH per AS (SELECT strftime(o_orderdate, '%Y-%m-%d') AS chain_id, count(*)::DOUBLE AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1),
tax AS (SELECT strftime(o_orderdate, '%Y-%m-%d') AS chain_id, round(avg(l_tax), 6) AS tax FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1),
c AS (SELECT chain_id, v.* FROM per LEFT JOIN tax USING (chain_id), LATERAL (VALUES (0, 'How many orders were placed that day?', n), (1, 'What is their total?', total), (2, 'What is the mean tax rate of their lines?', tax)) v(turn, query, answer)),
ch AS (SELECT *, answer IS NULL OR {det.sql_unit("'fail'", 'chain_id', 'turn')} < 0.1 AS failed FROM c) """


@query("fac_chains", CHAIN_SQL + "SELECT * FROM ch")
def fac_chains(t):
    return X.chains(t.orders, t.lineitem)


@query("fac_truncate", CHAIN_SQL + ", k AS (SELECT chain_id, min(turn) FILTER (WHERE failed) AS cut FROM ch GROUP BY 1) SELECT chain_id, turn, query, answer, failed FROM ch JOIN k USING (chain_id) WHERE cut IS NULL OR turn < cut")
def fac_truncate(t):
    return X.truncate(X.chains(t.orders, t.lineitem))


@query("fac_prompts", Q_SQL + "SELECT sample_id, replace(replace(([" + ", ".join("replace(" + _quote(p.replace("\n", "@@")) + ", '@@', chr(10))" for p in X.PROMPTS) + f"])[{det.sql_pick(len(X.PROMPTS), chr(39) + 'prompt' + chr(39), 'sample_id')} + 1], '{{t}}', table_id), '{{q}}', query) AS prompt FROM q")
def fac_prompts(t):
    return X.prompts(X.questions(t.spark))


@query("fac_shapes", D_SQL + "SELECT sample_id, 'thought' AS style, 'Thought: the question is a ' || class || ' on ' || table_id || '.' || chr(10) || 'Code: ' || gold_sql AS answer FROM d UNION ALL SELECT sample_id, 'observe', 'Act: ' || draft || chr(10) || 'Observe: ' || fault || chr(10) || 'Act: ' || gold_sql FROM d UNION ALL SELECT sample_id, 'plan', 'Plan: 1. read ' || table_id || ' 2. compute 3. report' || chr(10) || gold_sql || chr(10) || 'The result answers: ' || query FROM d")
def fac_shapes(t):
    d = X.drafts(X.questions(t.spark))
    return C.union_all([X.shape(d, s) for s in ("thought", "observe", "plan")])


def sql_samples(t, per_table=("orders", "customer", "part")):
    """Admissible statements of three tables: gold and drafts, a bounded list."""
    d = X.drafts(X.questions(t.spark)).where(F.col("table_id").isin(*per_table) & F.col("class").isin("retrieval", "computation", "statistics", "visualisation"))
    rows = d.orderBy("sample_id").collect()
    return [(f"{r.sample_id}/gold", r.gold_sql) for r in rows] + [(f"{r.sample_id}/draft", r.draft) for r in rows]


@query("fac_sql_exec")
def fac_sql_exec(t):
    """Every gold statement and draft run in a session of its own; status and error class of each."""
    return X.run_sql(t.spark, sql_samples(t), {n: getattr(t, n) for n in ("orders", "customer", "part")}).select("sample_id", "status", "error_class", "n_rows")


@query("fac_python_exec")
def fac_python_exec(t):
    """Small programs in child processes: one in five lacks a bracket, one asks for a missing key, one never ends."""
    base = t.nation.select(F.col("n_nationkey").cast("string").alias("sample_id"), F.when(F.col("n_nationkey") == 3, "while True: pass").when(F.col("n_nationkey") == 4, "print({}['a'])").when(F.col("n_nationkey") == 5, "open('/tmp/x', 'w').write('y')").when(F.col("n_nationkey") % 5 == 0, "print((1)").otherwise(F.concat(F.lit("print("), F.col("n_nationkey").cast("string"), F.lit(" * 2)"))).alias("code"))
    return X.run_python(base.repartition(4), seconds=1)


@query("fac_error_classes", "SELECT * FROM (VALUES ('UNRESOLVED_COLUMN.WITH_SUGGESTION', 'field_mismatch'), ('CAST_INVALID_INPUT', 'type_error'), ('PARSE_SYNTAX_ERROR', 'syntax'), ('JOB_CANCELLED', 'timeout'), ('EMPTY', 'empty'), ('', 'ok')) v(condition, error_class)")
def fac_error_classes(t):
    rows = [("UNRESOLVED_COLUMN.WITH_SUGGESTION",), ("CAST_INVALID_INPUT",), ("PARSE_SYNTAX_ERROR",), ("JOB_CANCELLED",), ("EMPTY",), ("",)]
    return t.spark.createDataFrame(rows, "condition string").withColumn("error_class", X.error_class(F.col("condition")))


@query("fac_redefines", D_SQL + "SELECT sample_id, regexp_matches(x, '(?i)create\\s+(temp\\w*\\s+)?(table|view)|pd\\.DataFrame\\s*\\(\\s*[\\[{]|with\\s+\\w+\\s+as\\s*\\(\\s*values') AS redefines FROM (SELECT sample_id, CASE WHEN fault = 'language' THEN 'df = pd.DataFrame([1])' WHEN fault = 'comment' THEN 'CREATE TABLE x AS ' || gold_sql ELSE draft END AS x FROM d)")
def fac_redefines(t):
    x = F.when(F.col("fault") == "language", "df = pd.DataFrame([1])").when(F.col("fault") == "comment", F.concat(F.lit("CREATE TABLE x AS "), "gold_sql")).otherwise(F.col("draft"))
    return X.drafts(X.questions(t.spark)).select("sample_id", X.redefines_table(x).alias("redefines"))


LANG_SQL = r"CASE WHEN regexp_matches(draft, '(?m)^\s*(import |from \w+ import|print\(|def )|\bpd\.') THEN 'python' WHEN regexp_matches(draft, '(?i)\b(select|insert|update|delete)\b') THEN 'sql' ELSE 'none' END"


@query("fac_wrong_language", D_SQL + f"SELECT fault, {LANG_SQL} AS found, count(*)::BIGINT AS n FROM d GROUP BY 1, 2")
def fac_wrong_language(t):
    return X.drafts(X.questions(t.spark)).select("fault", X.language_of(F.col("draft")).alias("found")).groupBy("fault", "found").agg(F.count("*").alias("n"))


COMMENT_SQL = r"trim(regexp_replace(regexp_replace(draft, '(?m)^\s*(--|#)[^\n]*$', '', 'g'), '\s+', '', 'g')) = ''"


@query("fac_comment_only", D_SQL + f"SELECT fault, {COMMENT_SQL} AS only_comments, count(*)::BIGINT AS n FROM d GROUP BY 1, 2")
def fac_comment_only(t):
    return X.drafts(X.questions(t.spark)).select("fault", X.comment_only(F.col("draft")).alias("only_comments")).groupBy("fault", "only_comments").agg(F.count("*").alias("n"))


SCORE_SQL = rf""", sc AS (SELECT sample_id, fault, draft, CASE WHEN contains(lower(draft), lower(table_id)) THEN 0.5 ELSE 0 END + CASE WHEN col = '' OR regexp_matches(draft, '\b' || col || '\b') THEN 0.5 ELSE 0 END AS coverage,
 least(1.0, len(regexp_split_to_array(trim(draft), '\s+')) / 4.0) AS detail, CASE WHEN {COMMENT_SQL} THEN 0.0 WHEN length(draft) > 400 THEN 0.5 ELSE 1.0 END AS clarity FROM d) """


@query("fac_scores", D_SQL + SCORE_SQL + "SELECT sample_id, 'field_coverage' AS scorer, coverage::DOUBLE AS value FROM sc UNION ALL SELECT sample_id, 'code_detail', detail::DOUBLE FROM sc UNION ALL SELECT sample_id, 'clarity', clarity::DOUBLE FROM sc")
def fac_scores(t):
    return X.score(X.drafts(X.questions(t.spark)))


@query("fac_keep", D_SQL + SCORE_SQL + "SELECT sample_id FROM sc WHERE least(coverage, detail, clarity) >= 0.75")
def fac_keep(t):
    return X.keep(X.score(X.drafts(X.questions(t.spark))))


@query("fac_calibrate", f"""WITH r AS (SELECT o_orderstatus AS batch, o_orderkey AS sample_id, {det.sql_unit("'ok'", 'o_orderkey')} >= 0.04 AS ok, row_number() OVER (PARTITION BY o_orderstatus ORDER BY {det.sql_text("'cal'", 'o_orderkey')}) AS r FROM orders),
g AS (SELECT batch, count(*)::BIGINT AS n, count(*) FILTER (WHERE ok)::BIGINT AS k FROM r WHERE r <= 300 GROUP BY 1), p AS (SELECT *, k::DOUBLE / n AS p, 1.96::DOUBLE AS z FROM g)
SELECT batch, n, k AS "right", round(p, 6) AS rate, round((p + z * z / (2 * n)) / (1 + z * z / n) - z * sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / (1 + z * z / n), 6) AS low, round((p + z * z / (2 * n)) / (1 + z * z / n) + z * sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / (1 + z * z / n), 6) AS high, p >= 0.95 AS passed FROM p""")
def fac_calibrate(t):
    rows = t.orders.select(F.col("o_orderstatus").alias("batch"), F.col("o_orderkey").alias("sample_id"), (det.unit("ok", F.col("o_orderkey")) >= 0.04).alias("right"))
    return X.calibrate(rows, 300)


@query("fac_validation", f"SELECT CASE WHEN {det.sql_unit(chr(39) + 'split' + chr(39), 'o_orderkey')} < 0.9 THEN 'train' ELSE 'valid' END AS part, count(*)::BIGINT AS n FROM orders GROUP BY 1")
def fac_validation(t):
    return t.orders.groupBy(F.when(det.unit("split", F.col("o_orderkey")) < 0.9, "train").otherwise("valid").alias("part")).agg(F.count("*").alias("n"))


@query("fac_review", D_SQL + "SELECT class, fault, count(*)::BIGINT AS n FROM d WHERE fault <> 'none' GROUP BY ROLLUP (class, fault)")
def fac_review(t):
    return X.drafts(X.questions(t.spark)).where("fault <> 'none'").rollup("class", "fault").agg(F.count("*").alias("n"))


PRED_SQL = "CASE " + " ".join(f"WHEN regexp_matches(lower(query), '{p}') THEN '{n}'" for n, p in X.CLASS_RULES) + " END"
FUNNEL_SQL = D_SQL + SCORE_SQL + rf""", ru AS (SELECT * FROM d WHERE NOT ({COMMENT_SQL}) AND {LANG_SQL} = 'sql'), s1 AS (SELECT ru.* FROM ru JOIN sc USING (sample_id) WHERE least(coverage, detail) >= 0.5),
 ex AS (SELECT * FROM s1 WHERE fault = 'none' AND class IN ('retrieval', 'computation', 'statistics', 'visualisation')), s2 AS (SELECT ex.* FROM ex JOIN sc USING (sample_id) WHERE least(coverage, detail, clarity) >= 0.75),
 ok AS (SELECT class FROM s2 GROUP BY 1 HAVING avg(({PRED_SQL} = class)::INT) >= 0.95), ga AS (SELECT * FROM s2 SEMI JOIN ok USING (class))
SELECT 0 AS step, 'generated' AS stage, count(*)::BIGINT AS kept FROM d UNION ALL SELECT 1, 'rules', count(*) FROM ru UNION ALL SELECT 2, 'scored', count(*) FROM s1 UNION ALL SELECT 3, 'executed', count(*) FROM ex
UNION ALL SELECT 4, 'scored_again', count(*) FROM s2 UNION ALL SELECT 5, 'gated', count(*) FROM ga UNION ALL SELECT 6, 'training', count(*) FROM ga WHERE {det.sql_unit("'split'", 'sample_id')} < 0.9"""


def star_tables(t):
    return {n: getattr(t, n) for n in X.SEMANTIC}


@query("fac_funnel", FUNNEL_SQL)
def fac_funnel(t):
    """Drafts and references are run; the oracle foresees from the planted faults which must end equal."""
    return M.funnel(X.staged(X.drafts(X.questions(t.spark)), star_tables(t)))


@query("fac_question_sets", Q_SQL + ", s AS (SELECT *, unnest([0, 1, 2]) AS set_id FROM q) SELECT set_id, table_id, sample_id, replace(replace(([" + ", ".join("replace(" + _quote(p.replace("\n", "@@")) + ", '@@', chr(10))" for p in X.PROMPTS) + f"])[{det.sql_pick(len(X.PROMPTS), chr(39) + 'set' + chr(39), 'set_id', 'sample_id')} + 1], '{{t}}', table_id), '{{q}}', query) AS prompt FROM s")
def fac_question_sets(t):
    """Three question sets for each table."""
    return X.question_sets(X.questions(t.spark))


@query("fac_registry", Q_SQL + ", g(generator, template) AS (VALUES " + ", ".join(f"({_quote(g)}, {_quote(p)})" for g, p in X.GENERATORS.items()) + ") SELECT generator, sample_id, replace(replace(template, '{k}', class), '{t}', table_id) AS prompt FROM q, g")
def fac_registry(t):
    """Each generator's prompt for its class of question, for every sample."""
    qs = X.questions(t.spark).join(F.broadcast(X.registry(t.spark)), "class")
    return qs.select("generator", "sample_id", F.replace("prompt", F.lit("{t}"), F.col("table_id")).alias("prompt"))


_KINDS = list(X.SFT_SHARES)


@query("fac_sft_mix", f"""
WITH d AS (SELECT o_orderkey, (['{"', '".join(_KINDS)}'])[{det.sql_pick(5, "'kind'", 'o_orderkey')} + 1] AS kind FROM orders), g(kind, target) AS (VALUES {', '.join(f"('{k}', {v}::DOUBLE)" for k, v in X.SFT_SHARES.items())}),
s AS (SELECT kind, count(*)::DOUBLE AS total FROM d GROUP BY 1), z AS (SELECT min(total / target) AS size FROM s JOIN g USING (kind)), r AS (SELECT kind, least(1.0, target * size / total) AS rate FROM s JOIN g USING (kind), z)
SELECT kind, count(*)::BIGINT AS n FROM d JOIN r USING (kind) WHERE {det.sql_unit("'mix'", 'o_orderkey')} < rate GROUP BY 1""")
def fac_sft_mix(t):
    d = t.orders.select("o_orderkey", F.get(F.array(*map(F.lit, _KINDS)), det.pick(5, "kind", F.col("o_orderkey"))).alias("kind"), F.lit(1).alias("one"))
    return C.to_ratio(d, "kind", "one", X.SFT_SHARES, "o_orderkey").groupBy("kind").agg(F.count("*").alias("n"))


@query("fac_blur_names", Q_SQL + "SELECT sample_id, replace(CASE WHEN col = '' THEN query ELSE replace(query, col, 'the ' || replace(regexp_replace(col, '^[a-z]+_', ''), '_', ' ')) END, ' ' || table_id, ' the data') AS query FROM q")
def fac_blur_names(t):
    return X.questions(t.spark).select("sample_id", X.blur_names(F.col("query"), F.col("table_id"), F.col("col")).alias("query"))


@query("fac_combine_turns", Q_SQL + f""", r AS (SELECT *, row_number() OVER (PARTITION BY table_id ORDER BY {det.sql_text("'turns'", 'sample_id')}) - 1 AS r FROM q), p AS (SELECT *, r // 2 AS pair FROM r),
j AS (SELECT *, {det.sql_unit("'join'", 'table_id', 'pair')} < 0.5 AS joined FROM p)
SELECT CASE WHEN joined THEN concat_ws('-', 'pair', table_id, pair) ELSE sample_id END AS sample_id, count(*)::BIGINT AS turns, string_agg(query, chr(10) ORDER BY r) AS text FROM j GROUP BY 1""")
def fac_combine_turns(t):
    return X.combine_turns(X.questions(t.spark))


@query("fac_append_requests", Q_SQL + f"SELECT sample_id, query || CASE WHEN {det.sql_unit(chr(39) + 'append' + chr(39), 'sample_id')} < 0.15 THEN ' Also draw a chart.' WHEN {det.sql_unit(chr(39) + 'append' + chr(39), 'sample_id')} < 0.3 THEN ' Sum up the result in one sentence.' ELSE '' END AS query FROM q")
def fac_append_requests(t):
    return X.append_requests(X.questions(t.spark))


@query("fac_tool_calls", Q_SQL + """SELECT sample_id, '{"tool":"query","arguments":{"table":"' || table_id || '","sql":"' || gold_sql || '"}}' AS call FROM q WHERE gold_sql IS NOT NULL""")
def fac_tool_calls(t):
    return X.tool_calls(X.questions(t.spark))


@query("fac_table_gen")
def fac_table_gen(t):
    return X.table_specs(t.part)


@query("fac_parse_receipts", "SELECT l_orderkey AS doc_id, l_partkey AS part, l_quantity AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def fac_parse_receipts(t):
    """Receipts written and read again: the rows come back."""
    return X.parse_receipts(X.receipts(t.orders, t.lineitem))


@query("fac_math", "SELECT p_partkey AS sample_id, 'What do ' || p_size || ' pieces at ' || p_retailprice || ' cost?' AS question, p_size || ' * ' || p_retailprice || ' = ' || printf('%.2f', round(p_size * p_retailprice, 2)) AS steps, round(p_size * p_retailprice, 2) AS answer FROM part")
def fac_math(t):
    return X.math_samples(t.part)


@query("met_executable")
def met_executable(t):
    runs = X.run_sql(t.spark, sql_samples(t, ("part",)), {"part": t.part})
    return runs.groupBy(F.split("sample_id", "/")[1].alias("side")).agg(F.count("*").alias("n"), F.round(F.avg((F.col("status") == "ok").cast("int")), 6).alias("executable"))


@query("met_key_error_rate")
def met_key_error_rate(t):
    runs = X.run_sql(t.spark, sql_samples(t, ("part",)), {"part": t.part})
    return runs.groupBy(F.split("sample_id", "/")[1].alias("side")).agg(F.round(F.avg((F.col("error_class") == "field_mismatch").cast("int")), 6).alias("key_error_rate"))
