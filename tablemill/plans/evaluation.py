"""Queries of the measures and of the published score tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.functions.lineage import cut
from tablemill.operators import corpus as C
from tablemill.operators import metrics as M
from tablemill.plans.registry import query

# Stand-in systems: the gold answer, two that err at a known rate, and the commonest answer.
SEG_SQL = f"""WITH gold AS (SELECT c_custkey AS sample_id, c_mktsegment AS gold FROM customer),
pred AS (SELECT sample_id, 'gold' AS system, gold AS pred FROM gold UNION ALL SELECT sample_id, 'noisy_10', CASE WHEN {det.sql_unit("'n'", 'sample_id')} < 0.1 THEN 'WRONG' ELSE gold END FROM gold
 UNION ALL SELECT sample_id, 'noisy_50', CASE WHEN {det.sql_unit("'n'", 'sample_id')} < 0.5 THEN 'WRONG' ELSE gold END FROM gold
 UNION ALL SELECT sample_id, 'majority', (SELECT gold FROM gold GROUP BY gold ORDER BY count(*) DESC, gold LIMIT 1) FROM gold) """


def segment_gold(t):
    return t.customer.select(F.col("c_custkey").alias("sample_id"), F.col("c_mktsegment").alias("gold"))


def segment_predictions(t):
    g = segment_gold(t)
    u = det.unit("n", F.col("sample_id"))
    top = g.groupBy("gold").count().orderBy(F.desc("count"), "gold").limit(1).select(F.col("gold").alias("top"))
    parts = [g.select("sample_id", F.lit("gold").alias("system"), F.col("gold").alias("pred"))]
    parts += [g.select("sample_id", F.lit(n).alias("system"), F.when(u < r, "WRONG").otherwise(F.col("gold")).alias("pred")) for n, r in (("noisy_10", 0.1), ("noisy_50", 0.5))]
    parts.append(g.crossJoin(F.broadcast(top)).select("sample_id", F.lit("majority").alias("system"), F.col("top").alias("pred")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query("met_accuracy", SEG_SQL + "SELECT system, count(*)::BIGINT AS n, sum((pred = gold)::INT)::BIGINT AS correct, round(avg((pred = gold)::INT), 6) AS accuracy FROM pred JOIN gold USING (sample_id) GROUP BY 1")
def met_accuracy(t):
    return M.accuracy(segment_predictions(t), segment_gold(t))


@query("met_micro_f1", SEG_SQL + "SELECT sum((pred = gold)::INT)::BIGINT AS tp, sum((pred <> gold)::INT)::BIGINT AS fp, sum((pred <> gold)::INT)::BIGINT AS fn, round(avg((pred = gold)::INT), 6) AS f1 FROM pred JOIN gold USING (sample_id) WHERE system = 'noisy_10'")
def met_micro_f1(t):
    p = segment_predictions(t).where("system = 'noisy_10'").select("sample_id", F.col("pred").alias("label"))
    return M.micro_f1(p, segment_gold(t).select("sample_id", F.col("gold").alias("label")))


@query("met_prf", SEG_SQL + """, b AS (SELECT gold AS g, pred AS p FROM pred JOIN gold USING (sample_id) WHERE system = 'noisy_50'), l AS (SELECT g AS label FROM b UNION SELECT p FROM b)
SELECT label, round(coalesce(count(*) FILTER (WHERE g = label AND p = label)::DOUBLE / nullif(count(*) FILTER (WHERE p = label), 0), 0), 6) AS precision, round(coalesce(count(*) FILTER (WHERE g = label AND p = label)::DOUBLE / nullif(count(*) FILTER (WHERE g = label), 0), 0), 6) AS recall,
 round(2.0::DOUBLE * count(*) FILTER (WHERE g = label AND p = label) / (count(*) FILTER (WHERE p = label) + count(*) FILTER (WHERE g = label)), 6) AS f1 FROM b, l GROUP BY label""")
def met_prf(t):
    p = segment_predictions(t).where("system = 'noisy_50'").select("sample_id", F.col("pred").alias("label"))
    return M.prf(p, segment_gold(t).select("sample_id", F.col("gold").alias("label")))


RANK_SQL = f"""WITH ranked AS (SELECT p_brand AS query_id, p_partkey AS item, row_number() OVER (PARTITION BY p_brand ORDER BY {det.sql_text("'rank'", 'p_partkey')})::INT AS rank FROM part),
rel AS (SELECT p_brand AS query_id, p_partkey AS item FROM part WHERE p_size <= 10), n AS (SELECT query_id, count(*) AS n FROM rel GROUP BY 1)"""


def rankings(t):
    from pyspark.sql import Window

    w = Window.partitionBy("p_brand").orderBy(det.text("rank", F.col("p_partkey")))
    ranked = t.part.select(F.col("p_brand").alias("query_id"), F.col("p_partkey").alias("item"), F.row_number().over(w).alias("rank"))
    return ranked, t.part.where("p_size <= 10").select(F.col("p_brand").alias("query_id"), F.col("p_partkey").alias("item"))


@query("met_map", RANK_SQL + ", h AS (SELECT query_id, rank, row_number() OVER (PARTITION BY query_id ORDER BY rank) AS i FROM ranked SEMI JOIN rel USING (query_id, item)), s AS (SELECT query_id, sum(i::DOUBLE / rank) AS s FROM h GROUP BY 1) SELECT count(*)::BIGINT AS queries, round(avg(coalesce(s, 0) / n), 6) AS map FROM n LEFT JOIN s USING (query_id)")
def met_map(t):
    return M.mean_ap(*rankings(t))


@query("met_recall_at_k", RANK_SQL + ", h AS (SELECT query_id, count(*) AS h, min(rank) AS best FROM ranked SEMI JOIN rel USING (query_id, item) WHERE rank <= 20 GROUP BY 1) SELECT count(*)::BIGINT AS queries, round(avg(coalesce(h, 0)::DOUBLE / n), 6) AS recall, round(avg(coalesce(1.0::DOUBLE / best, 0)), 6) AS mrr FROM n LEFT JOIN h USING (query_id)")
def met_recall_at_k(t):
    return M.recall_at(*rankings(t), 20)


@query("met_exec_acc", f"""WITH g AS (SELECT o_custkey AS sample_id, md5(o_orderkey || '|' || o_totalprice) AS row_hash FROM orders), r AS (SELECT * FROM g WHERE {det.sql_unit("'drop'", 'row_hash')} >= 0.02),
k AS (SELECT sample_id, count(*) AS n FROM g GROUP BY 1), m AS (SELECT sample_id, count(*) AS n FROM r GROUP BY 1)
SELECT count(*)::BIGINT AS samples, sum((k.n = coalesce(m.n, 0))::INT)::BIGINT AS correct, round(avg((k.n = coalesce(m.n, 0))::INT), 6) AS exec_acc FROM k LEFT JOIN m USING (sample_id)""")
def met_exec_acc(t):
    g = t.orders.select(F.col("o_custkey").alias("sample_id"), F.md5(F.concat_ws("|", F.col("o_orderkey").cast("string"), F.col("o_totalprice").cast("string"))).alias("row_hash"))
    return M.exec_acc(g.where(det.unit("drop", F.col("row_hash")) >= 0.02), g)


PAIRS_SQL = """WITH p AS (SELECT c_custkey AS sample_id, string_split('customer ' || c_name || ' of segment ' || lower(c_mktsegment) || ' has a balance of ' || c_acctbal, ' ') AS gold,
 string_split('the customer ' || c_name || ' has a balance of ' || c_acctbal || ' in segment ' || lower(c_mktsegment), ' ') AS pred FROM customer)"""


def sentence_pairs(t):
    """One sentence of facts about each customer in two wordings."""
    name, seg, bal = F.col("c_name"), F.lower("c_mktsegment"), F.col("c_acctbal").cast("string")
    gold = F.concat(F.lit("customer "), name, F.lit(" of segment "), seg, F.lit(" has a balance of "), bal)
    pred = F.concat(F.lit("the customer "), name, F.lit(" has a balance of "), bal, F.lit(" in segment "), seg)
    return t.customer.select(F.col("c_custkey").alias("sample_id"), F.split(gold, " ").alias("gold"), F.split(pred, " ").alias("pred"))


def bleu_sql(pairs):
    def grams(c, n):
        return f"list_transform(range(1, len({c}) - {n - 2}), lambda i: array_to_string({c}[i:i+{n - 1}], ' '))"

    parts = " UNION ALL ".join(f"SELECT sample_id, {n} AS n, unnest({grams(c, n)}) AS g, {int(c == 'pred')} AS p, {int(c == 'gold')} AS r FROM p" for n in (1, 2, 3, 4) for c in ("pred", "gold"))
    return pairs + f""", g AS ({parts}), c AS (SELECT sample_id, n, g, sum(p) AS p, sum(r) AS r FROM g GROUP BY 1, 2, 3), o AS (SELECT n, sum(least(p, r)) AS m, sum(p) AS t FROM c GROUP BY 1),
z AS (SELECT count(*)::BIGINT AS samples, sum(len(pred)) AS c, sum(len(gold)) AS r FROM p)
SELECT any_value(samples) AS samples, round(CASE WHEN min(m) > 0 THEN 100 * CASE WHEN any_value(z.c) >= any_value(z.r) THEN 1 ELSE exp(1 - any_value(z.r)::DOUBLE / any_value(z.c)) END * exp(avg(ln(m::DOUBLE / t))) ELSE 0 END, 4) AS bleu FROM o, z"""


@query("met_bleu", bleu_sql(PAIRS_SQL))
def met_bleu(t):
    return M.bleu(sentence_pairs(t))


@query("met_sentence_bleu")
def met_sentence_bleu(t):
    return M.sentence_bleu(sentence_pairs(t))


@query("met_rouge_l")
def met_rouge_l(t):
    return M.rouge_l(sentence_pairs(t))


TRIES_SQL = f"WITH r AS (SELECT p_partkey AS problem, i, {det.sql_unit(chr(39) + 'try' + chr(39), 'p_partkey', 'i')} < 0.4 AS ok FROM part, range(5) x(i)), c AS (SELECT problem, count(*) AS n, count(*) FILTER (WHERE ok) AS c FROM r GROUP BY 1)"


def tries(t, n=5):
    return t.part.select(F.col("p_partkey").alias("problem"), F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("i")).select("problem", (det.unit("try", F.col("problem"), F.col("i")) < 0.4).alias("ok"))


for _k in (1, 3):

    @query("met_pass_at_k" if _k == 1 else f"met_pass_at_{_k}", TRIES_SQL + f" SELECT {_k} AS k, count(*)::BIGINT AS problems, round(avg(1 - CASE WHEN n - c < {_k} THEN 0 ELSE coalesce(list_product(list_transform(range(n - c + 1, n + 1), lambda i: 1 - {_k}::DOUBLE / i)), 1) END), 6) AS pass_at_k FROM c")
    def met_pass(t, k=_k):
        return M.pass_at_k(tries(t), k)


JUDGE_SQL = """WITH j AS (SELECT c_custkey AS sample_id, CASE WHEN c_custkey % 3 = 0 THEN c_name || ' balance unknown' WHEN c_custkey % 50 = 1 THEN 'drop table customer' ELSE c_name || ' balance ' || c_acctbal END AS pred, c_name || ' balance ' || c_acctbal AS gold, [c_name, c_acctbal::VARCHAR] AS facts FROM customer),
w AS (SELECT *, list_distinct(regexp_extract_all(lower(pred), '[a-z0-9.]+')) AS p, list_distinct(regexp_extract_all(lower(gold), '[a-z0-9.]+')) AS g FROM j),
s AS (SELECT sample_id, round(200.0::DOUBLE * len(list_intersect(p, g)) / (len(p) + len(g)), 4) AS consistency, round(100.0::DOUBLE * len(list_filter(facts, lambda x: contains(lower(pred), lower(x)))) / len(facts), 4) AS completeness, CASE WHEN regexp_matches(lower(pred), 'drop table|password|rm -rf|import os') THEN 0.0 ELSE 100.0 END::DOUBLE AS security FROM w)"""


def judged(t):
    name, bal = F.col("c_name"), F.col("c_acctbal").cast("string")
    gold = F.concat(name, F.lit(" balance "), bal)
    pred = F.when(F.col("c_custkey") % 3 == 0, F.concat(name, F.lit(" balance unknown"))).when(F.col("c_custkey") % 50 == 1, "drop table customer").otherwise(gold)
    return t.customer.select(F.col("c_custkey").alias("sample_id"), pred.alias("pred"), gold.alias("gold"), F.array(name, bal).alias("facts"))


@query("met_judge", JUDGE_SQL + " SELECT *, round((consistency + completeness + security) / 3, 4) AS total FROM s")
def met_judge(t):
    return M.judge(judged(t))


@query("met_judge_combine", JUDGE_SQL + " SELECT sample_id, round(CASE WHEN sample_id % 4 = 0 THEN 0.5 * consistency + 0.5 * completeness ELSE completeness END, 4) AS score FROM s")
def met_judge_combine(t):
    s = M.judge(judged(t)).select("sample_id", F.when(F.col("sample_id") % 4 == 0, F.col("consistency")).alias("human"), F.col("completeness").alias("machine"))
    return M.combine(s).select("sample_id", F.round("score", 4).alias("score"))


@query("met_token_length", r"""WITH p AS (SELECT lang, len(regexp_extract_all(text, '\S+'))::BIGINT AS n FROM documents) SELECT lang, min(n) AS low, max(n) AS high, median(n) AS mid FROM p GROUP BY 1""")
def met_token_length(t):
    p = t.documents.select("lang", F.size(F.regexp_extract_all("text", F.lit(r"\S+"), F.lit(0))).cast("long").alias("n"))
    return p.groupBy("lang").agg(F.min("n").alias("low"), F.max("n").alias("high"), F.percentile("n", 0.5).alias("mid"))


@query("met_truncation", r"""WITH d AS (SELECT doc_id, len(regexp_extract_all(text, '\S+'))::BIGINT AS n FROM documents) SELECT count(*)::BIGINT AS docs, sum((n > 512)::INT)::BIGINT AS longer, round(avg((n > 512)::INT), 6) AS share FROM d""")
def met_truncation(t):
    d = t.documents.select(F.size(F.regexp_extract_all("text", F.lit(r"\S+"), F.lit(0))).alias("n"))
    return d.agg(F.count("*").alias("docs"), F.sum((F.col("n") > 512).cast("int")).alias("longer"), F.round(F.avg((F.col("n") > 512).cast("int")), 6).alias("share"))


SCORES_SQL = "WITH s(table_no, metric, system, value) AS (VALUES " + ", ".join(f"({a}, '{b}', '{c}', {d}::DOUBLE)" for a, b, c, d in M.published()) + ") "
OPEN = "(" + ", ".join(f"'{c}'" for c in M.COMPARATORS) + ")"


def _gain_sql(ours, tables):
    return f"SELECT b.system, '{ours}' AS ours, count(*)::BIGINT AS n_rows, round(100 * (avg(a.value) / avg(b.value) - 1), 2) AS gain FROM s a JOIN s b USING (table_no, metric) WHERE a.system = '{ours}' AND b.system IN {OPEN} AND table_no IN {tables} GROUP BY 1"


def _wins_sql(ours):
    return f"SELECT '{ours}' AS ours, count(*)::BIGINT AS n_rows, sum((value > best)::INT)::BIGINT AS wins FROM s JOIN (SELECT metric, max(value) AS best FROM s WHERE table_no = 5 AND system IN {OPEN} GROUP BY 1) USING (metric) WHERE table_no = 5 AND system = '{ours}'"


# Rules that tell good documents, as systems of a board: two of ours, three to compare with.
RULES = {"both": "n >= 50 AND ends", "either": "n >= 50 OR ends", "length": "n >= 50", "ends": "ends", "lines": "broken"}
OURS, OTHERS = ["both", "either"], ["length", "ends", "lines"]
BOARD_SQL = r"""WITH d AS (SELECT lang, source, quality, len(regexp_extract_all(coalesce(text, ''), '\S+')) AS n, contains(coalesce(text, ''), '.') AS ends, contains(coalesce(text, ''), chr(10)) AS broken FROM documents JOIN labels USING (doc_id) WHERE quality IS NOT NULL),
h AS (SELECT """ + ", ".join(f"""(({rule}) = (quality = 1))::INT AS "{name}" """ for name, rule in RULES.items()) + """, lang, source FROM d),
g AS (SELECT 5 AS table_no, coalesce(lang, 'none') AS metric, * FROM h UNION ALL SELECT 6, coalesce(source, 'none'), * FROM h),
s AS (""" + " UNION ALL ".join(f"""SELECT table_no, metric, '{name}' AS system, round(100 * avg("{name}"), 4) AS value FROM g GROUP BY 1, 2""" for name in RULES) + ") "
RIVALS = "(" + ", ".join(f"'{c}'" for c in OTHERS) + ")"


def scores(t):
    """Accuracy of the rules against the labels, by language (table 5) and by source (table 6)."""
    text = F.coalesce("text", F.lit(""))
    rows = t.documents.join(t.labels, "doc_id").select("lang", "source", "quality", F.size(F.regexp_extract_all(text, F.lit(r"\S+"), F.lit(0))).alias("n"), text.contains(".").alias("ends"), text.contains("\n").alias("broken"))
    return M.measured(rows, {name: F.expr(rule) for name, rule in RULES.items()}, F.col("quality") == 1, {5: F.col("lang"), 6: F.col("source")})


def _board_gain_sql(ours):
    return f"SELECT b.system, '{ours}' AS ours, count(*)::BIGINT AS n_rows, round(100 * (avg(a.value) / avg(b.value) - 1), 2) AS gain FROM s a JOIN s b USING (table_no, metric) WHERE a.system = '{ours}' AND b.system IN {RIVALS} GROUP BY 1"


@query("board_improvement", BOARD_SQL + " UNION ALL ".join(map(_board_gain_sql, OURS)))
def board_improvement(t):
    s = cut(scores(t))
    return C.union_all([M.improvement(s, ours, [5, 6], OTHERS) for ours in OURS])


def _board_wins_sql(ours):
    return f"SELECT '{ours}' AS ours, count(*)::BIGINT AS n_rows, coalesce(sum((value > best)::INT), 0)::BIGINT AS wins FROM s JOIN (SELECT metric, max(value) AS best FROM s WHERE table_no = 5 AND system IN {RIVALS} GROUP BY 1) USING (metric) WHERE table_no = 5 AND system = '{ours}'"


@query("board_wins", BOARD_SQL + " UNION ALL ".join(map(_board_wins_sql, OURS)))
def board_wins(t):
    s = cut(scores(t))
    return C.union_all([M.wins(s, ours, 5, OTHERS) for ours in OURS])


@query("board_delta", BOARD_SQL + "SELECT metric, round(a.value - b.value, 4) AS delta FROM s a JOIN s b USING (table_no, metric) WHERE table_no = 6 AND a.system = 'both' AND b.system = 'length'")
def board_delta(t):
    return M.delta(cut(scores(t)), "both", "length", 6)


@query("board_eligible", BOARD_SQL + ", m AS (SELECT system, round(avg(value), 4) AS mean FROM s WHERE table_no = 6 GROUP BY 1) SELECT system, mean, mean >= 0.9 * (SELECT mean FROM m WHERE system = 'length') AS eligible FROM m")
def board_eligible(t):
    return M.eligible(cut(scores(t)), "length", 0.9, 6)


@query("board_volume", r"SELECT 'documents' AS kind, count(*)::BIGINT AS n, count(DISTINCT source)::BIGINT AS sources, sum(len(regexp_extract_all(text, '\S+')))::BIGINT AS tokens FROM documents UNION ALL SELECT 'dialogues', count(DISTINCT conv_id), 1, sum(len(regexp_extract_all(text, '\S+')))::BIGINT FROM conversations")
def board_volume(t):
    n = F.size(F.regexp_extract_all("text", F.lit(r"\S+"), F.lit(0)))
    a = t.documents.agg(F.lit("documents").alias("kind"), F.count("*").alias("n"), F.countDistinct("source").alias("sources"), F.sum(n).alias("tokens"))
    return a.unionByName(t.conversations.agg(F.lit("dialogues").alias("kind"), F.countDistinct("conv_id").alias("n"), F.lit(1).cast("long").alias("sources"), F.sum(n).alias("tokens")))
