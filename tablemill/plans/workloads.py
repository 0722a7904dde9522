"""The experiment workloads, re-expressed on the given tables: a generator of questions with gold answers, a stand-in predictor, the measure."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.functions.lineage import cut
from tablemill.functions.text import lines
from tablemill.operators import agent as A
from tablemill.operators import corpus as C
from tablemill.operators import encoder as E
from tablemill.operators import factory as X
from tablemill.operators import metrics as M
from tablemill.operators import samples
from tablemill.operators import tables as T
from tablemill.plans import agent as agent_plans
from tablemill.plans import encoder as encoder_plans
from tablemill.plans import tables as table_plans
from tablemill.plans.corpus import NEAR_SQL, TOK
from tablemill.plans.evaluation import JUDGE_SQL, SCORES_SQL, _gain_sql, _wins_sql, bleu_sql, sentence_pairs
from tablemill.plans.evaluation import PAIRS_SQL as CUSTOMER_PAIRS
from tablemill.plans.registry import dealt, query

STARS = ("customer", "supplier", "part", "orders", "nation")


def star_cells(t, names=STARS):
    return C.union_all([T.melt(dealt(getattr(t, n)), n, X.KEY_OF[n], list(X.SEMANTIC[n])) for n in names])


# --- table understanding -----------------------------------------------------


def guess_type(prof):
    """Rule predictor on the values alone: type, share of distinct values, number of kinds."""
    ratio = F.col("n_distinct") / F.col("n")
    return prof.withColumn("label", F.when(F.col("dtype") == "timestamp", "date").when((F.col("dtype") == "long") & (ratio > 0.9), "key").when(F.col("dtype") == "long", "quantity").when(F.col("dtype") == "double", "money").when(ratio > 0.9, "name").when(F.col("n_distinct") <= 30, "category").otherwise("text"))


@query("w01")
def w01(t):
    """Column types: micro F1 of the rule predictor over all star columns."""
    prof = guess_type(T.profile(star_cells(t))).select(F.concat_ws(".", "table_id", "col_name").alias("sample_id"), "label")
    gold = t.spark.createDataFrame([(f"{n}.{c}", s) for n in STARS for c, s in X.SEMANTIC[n].items()], "sample_id string, label string")
    return M.micro_f1(prof, gold)


@query("w01b", """
WITH s AS (SELECT a.vec_id, a.label, b.label AS pred, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: z[1]::DOUBLE * z[2]::DOUBLE)), 6) DESC, b.vec_id) AS rk
 FROM embeddings a JOIN embeddings b ON a.vec_id % 20 = 0 AND a.vec_id <> b.vec_id)
SELECT 1 AS k, sum((label = pred)::INT)::BIGINT AS correct, count(*)::BIGINT AS total FROM s WHERE rk = 1""")
def w01b(t):
    return encoder_plans.vec_knn_label(t).select(F.lit(1).alias("k"), "correct", "total")


RELATIONS = [("orders", "o_custkey", "customer", "c_custkey"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("supplier", "s_nationkey", "nation", "n_nationkey")]
_REL_VALUES = {"orders": ["o_custkey"], "customer": ["c_custkey", "c_nationkey"], "supplier": ["s_suppkey", "s_nationkey"], "nation": ["n_nationkey", "n_regionkey"], "part": ["p_partkey"]}
W02_SQL = (
    "WITH v AS (" + " UNION ".join(f"SELECT DISTINCT '{n}' AS table_id, '{c}' AS col_name, {c}::VARCHAR AS value FROM {n}" for n, cs in _REL_VALUES.items() for c in cs) + "), n AS (SELECT table_id, col_name, count(*) AS n FROM v GROUP BY 1, 2), "
    "c AS (SELECT a.table_id, a.col_name AS from_col, b.table_id AS in_table, b.col_name AS to_col, round(count(*)::DOUBLE / any_value(n.n), 6) AS containment FROM v a JOIN v b ON a.value = b.value AND a.table_id <> b.table_id JOIN n ON n.table_id = a.table_id AND n.col_name = a.col_name GROUP BY 1, 2, 3, 4) "
    "SELECT from_col, to_col, containment, containment = 1 AND to_col IN ('c_custkey', 's_suppkey', 'n_nationkey', 'p_partkey') AS predicted, (from_col, to_col) IN (" + ", ".join(f"('{a[1]}', '{a[3]}')" for a in RELATIONS) + ") AS gold FROM c"
)


@query("w02", W02_SQL)
def w02(t):
    """Relations between columns: contained values and a unique parent predict a foreign key; small integers also fit by chance."""
    cells = C.union_all([T.melt(getattr(t, n), n, X.KEY_OF[n], cs) for n, cs in _REL_VALUES.items()])
    inc = T.inclusions(cells)
    gold = None
    for _, a, _, b in RELATIONS:
        hit = (F.col("col_name") == a) & (F.col("in_col") == b)
        gold = hit if gold is None else gold | hit
    unique = F.col("in_col").isin("c_custkey", "s_suppkey", "n_nationkey", "p_partkey")
    return inc.select(F.col("col_name").alias("from_col"), F.col("in_col").alias("to_col"), "containment", ((F.col("containment") == 1) & unique).alias("predicted"), gold.alias("gold"))


W03_SQL = f"""WITH m AS (SELECT s_suppkey AS gold, CASE {det.sql_pick(3, "'noise'", 's_suppkey')} WHEN 0 THEN upper(s_name) WHEN 1 THEN replace(s_name, '#', ' ') ELSE regexp_replace(s_name, '#0+', '#') END AS mention FROM supplier),
c AS (SELECT m.gold, s.s_suppkey, row_number() OVER (PARTITION BY m.gold ORDER BY levenshtein(lower(m.mention), lower(s.s_name)), s.s_suppkey) AS r FROM m JOIN supplier s ON regexp_extract(m.mention, '[0-9]+$')::BIGINT = regexp_extract(s.s_name, '[0-9]+$')::BIGINT)
SELECT sum((gold = s_suppkey)::INT)::BIGINT AS correct, count(*)::BIGINT AS total, round(avg((gold = s_suppkey)::INT), 6) AS accuracy FROM c WHERE r = 1"""


@query("w03", W03_SQL)
def w03(t):
    """Noisy supplier names linked to the nearest name that ends in the same number, however it is written."""
    number = lambda c: F.regexp_extract(c, "([0-9]+)$", 1).cast("long")
    k = det.pick(3, "noise", F.col("s_suppkey"))
    m = t.supplier.select(F.col("s_suppkey").alias("gold"), F.when(k == 0, F.upper("s_name")).when(k == 1, F.replace("s_name", F.lit("#"), F.lit(" "))).otherwise(F.regexp_replace("s_name", "#0+", "#")).alias("mention")).withColumn("block", number("mention"))
    c = m.join(t.supplier.withColumn("block", number("s_name")), "block")
    w = Window.partitionBy("gold").orderBy(F.levenshtein(F.lower("mention"), F.lower("s_name")), "s_suppkey")
    best = c.withColumn("r", F.row_number().over(w)).where("r = 1")
    ok = (F.col("gold") == F.col("s_suppkey")).cast("int")
    return best.agg(F.sum(ok).alias("correct"), F.count("*").alias("total"), F.round(F.avg(ok), 6).alias("accuracy"))


W04_SQL = """WITH p AS (SELECT p_brand || '/' || p_type AS query_id, p_partkey, p_brand, p_size, row_number() OVER (PARTITION BY p_brand, p_type ORDER BY p_partkey) AS r FROM part),
s AS (SELECT query_id, any_value(p_brand) AS brand, avg(p_size) AS size FROM p WHERE r <= 2 GROUP BY 1), rel AS (SELECT query_id, p_partkey AS item FROM p WHERE r > 2),
c AS (SELECT s.query_id, p.p_partkey AS item, row_number() OVER (PARTITION BY s.query_id ORDER BY abs(p.p_size - s.size), p.p_partkey) AS rank FROM s JOIN p ON p.p_brand = s.brand WHERE NOT (p.query_id = s.query_id AND p.r <= 2)),
h AS (SELECT query_id, rank, row_number() OVER (PARTITION BY query_id ORDER BY rank) AS i FROM c SEMI JOIN rel USING (query_id, item)), a AS (SELECT query_id, sum(i::DOUBLE / rank) AS s FROM h GROUP BY 1), n AS (SELECT query_id, count(*) AS n FROM rel GROUP BY 1)
SELECT count(*)::BIGINT AS queries, round(avg(coalesce(s, 0) / n), 6) AS map FROM n LEFT JOIN a USING (query_id)"""


@query("w04", W04_SQL)
def w04(t):
    """Rows to add to a table of one brand and type, ranked by closeness of size to two seed rows."""
    w = Window.partitionBy("p_brand", "p_type").orderBy("p_partkey")
    p = t.part.select(F.concat_ws("/", "p_brand", "p_type").alias("query_id"), "p_partkey", "p_brand", "p_size", F.row_number().over(w).alias("r"))
    seeds = p.where("r <= 2").groupBy("query_id").agg(F.first("p_brand").alias("p_brand"), F.avg("p_size").alias("size"))
    cand = seeds.withColumnRenamed("query_id", "q").join(p, "p_brand").where("not (query_id = q and r <= 2)")
    ranked = cand.select(F.col("q").alias("query_id"), F.col("p_partkey").alias("item"), F.row_number().over(Window.partitionBy("q").orderBy(F.abs(F.col("p_size") - F.col("size")), "p_partkey")).alias("rank"))
    return M.mean_ap(ranked, p.where("r > 2").select("query_id", F.col("p_partkey").alias("item")))


# --- question answering ------------------------------------------------------


@query("w05", table_plans.GRID_SQL + ", q AS (SELECT col_name AS question_id, split_part(col_name, ' / ', 1) AS region, b.y AS year, value::BIGINT AS value FROM fl JOIN yr ON yr.r = fl.row_id JOIN (SELECT DISTINCT y FROM base) b ON b.y = yr.y WHERE col_id > 0) SELECT question_id, region, year, q.value, base.v AS gold, q.value = base.v AS ok FROM q JOIN base ON base.r_name || ' / ' || base.n_name = question_id AND base.y = year")
def w05(t):
    """A merged-header table answers by its flattened form; gold comes straight from the star tables."""
    flat = T.flatten_headers(T.unmerge(table_plans.grid(t)))
    years = flat.where("col_id = 0").select("row_id", F.col("value").try_cast("int").alias("year"))
    q = flat.where("col_id > 0").join(years, "row_id").select(F.col("col_name").alias("question_id"), F.split("col_name", " / ")[0].alias("region"), "year", F.col("value").try_cast("long").alias("value"))
    both = t.orders.join(t.customer, F.col("o_custkey") == F.col("c_custkey")).join(t.nation, F.col("c_nationkey") == F.col("n_nationkey")).join(t.region, F.col("n_regionkey") == F.col("r_regionkey"))
    gold = both.groupBy(F.concat_ws(" / ", "r_name", "n_name").alias("question_id"), F.year("o_orderdate").alias("year")).agg(F.round(F.sum("o_totalprice")).cast("long").alias("gold"))
    return q.join(gold, ["question_id", "year"]).select("question_id", "region", "year", "value", "gold", (F.col("value") == F.col("gold")).alias("ok"))


@query("w05_raw_contrast")
def w05_raw_contrast(t):
    """Share of cells found by 'region / nation' names: the grid used raw has one name only per header cell, the normalised one all."""
    g = table_plans.grid(t)
    body = g.where("not is_header and c > 0")
    raw_names = g.where("is_header and r = 0").select("table_id", "c", F.col("value").alias("region"))
    raw = body.join(raw_names, ["table_id", "c"], "left").agg(F.lit("raw").alias("way"), F.round(F.avg(F.col("region").isNotNull().cast("int")), 6).alias("exec_acc"))
    return raw.unionByName(w05(t).agg(F.lit("normalised").alias("way"), F.round(F.avg(F.col("ok").cast("int")), 6).alias("exec_acc")))


ORDER_PAIRS = """WITH p AS (SELECT o_orderkey AS sample_id, string_split('order ' || o_orderkey || ' of customer ' || o_custkey || ' costs ' || o_totalprice || ' and has priority ' || o_orderpriority, ' ') AS gold,
 string_split('order ' || o_orderkey || ' has priority ' || o_orderpriority || ' and costs ' || o_totalprice || ' for customer ' || o_custkey, ' ') AS pred FROM orders)"""


@query("w06", bleu_sql(ORDER_PAIRS))
def w06(t):
    """Free answers on one order in two wordings."""
    s = lambda c: F.col(c).cast("string")
    gold = F.concat(F.lit("order "), s("o_orderkey"), F.lit(" of customer "), s("o_custkey"), F.lit(" costs "), s("o_totalprice"), F.lit(" and has priority "), "o_orderpriority")
    pred = F.concat(F.lit("order "), s("o_orderkey"), F.lit(" has priority "), "o_orderpriority", F.lit(" and costs "), s("o_totalprice"), F.lit(" for customer "), s("o_custkey"))
    return M.bleu(t.orders.select(F.col("o_orderkey").alias("sample_id"), F.split(gold, " ").alias("gold"), F.split(pred, " ").alias("pred")))


def _grams8(c="ws"):
    return f"CASE WHEN len({c}) >= 8 THEN list_transform(range(1, len({c}) - 6), lambda i: array_to_string({c}[i:i+7], ' ')) ELSE [] END"


W07_SQL = f"""WITH w AS (SELECT doc_id, regexp_extract_all(lower(text), '\\S+') AS ws FROM documents), b AS (SELECT item_id, regexp_extract_all(lower(text), '\\S+') AS ws FROM benchmark),
g AS (SELECT DISTINCT item_id, unnest({_grams8()}) AS g FROM b), o AS (SELECT doc_id, unnest(list_distinct({_grams8()})) AS g FROM w), h AS (SELECT DISTINCT doc_id FROM o JOIN g USING (g))
SELECT CASE WHEN quality IS NULL THEN 'unknown' WHEN quality = 1 THEN 'good' ELSE 'poor' END AS verdict, count(*)::BIGINT AS n FROM h LEFT JOIN labels USING (doc_id) GROUP BY 1"""


@query("w07", W07_SQL)
def w07(t):
    """Two hops: the documents that hold a test passage, then their quality label."""
    hits = C.decontaminate(t.documents, t.benchmark).select("doc_id")
    v = F.when(F.col("quality").isNull(), "unknown").when(F.col("quality") == 1, "good").otherwise("poor")
    return hits.join(t.labels, "doc_id", "left").groupBy(v.alias("verdict")).agg(F.count("*").alias("n"))


@query("w08", "SELECT c_mktsegment || '/' || m AS question_id, round(CASE m WHEN 'count' THEN count(*) WHEN 'mean' THEN avg(c_acctbal) WHEN 'max' THEN max(c_acctbal) ELSE min(c_acctbal) END, 4)::DOUBLE AS answer FROM customer, (VALUES ('count'), ('mean'), ('max'), ('min')) v(m) GROUP BY c_mktsegment, m")
def w08(t):
    """Select, where, aggregate on one table: four measures of each segment."""
    g = t.customer.groupBy("c_mktsegment").agg(F.count("*").cast("double").alias("count"), F.avg("c_acctbal").alias("mean"), F.max("c_acctbal").alias("max"), F.min("c_acctbal").alias("min"))
    return g.unpivot("c_mktsegment", ["count", "mean", "max", "min"], "m", "v").select(F.concat_ws("/", "c_mktsegment", "m").alias("question_id"), F.round("v", 4).alias("answer"))


@query("w09", """SELECT 'dearest' AS question_id, max(p_retailprice)::DOUBLE AS answer FROM part UNION ALL SELECT 'urgent minus low', (count(*) FILTER (WHERE o_orderpriority = '1-URGENT') - count(*) FILTER (WHERE o_orderpriority = '5-LOW'))::DOUBLE FROM orders
UNION ALL SELECT 'over 300000', count(*)::DOUBLE FROM orders WHERE o_totalprice > 300000 UNION ALL SELECT 'after key 10', min(o_orderkey)::DOUBLE FROM orders WHERE o_orderkey > 10 UNION ALL SELECT 'nations of first region', count(*)::DOUBLE FROM nation WHERE n_regionkey = 0""")
def w09(t):
    """Compositions: superlative, difference, threshold count, next row, join."""
    row = lambda name, df: df.select(F.lit(name).alias("question_id"), F.col(df.columns[0]).cast("double").alias("answer"))
    o = t.orders
    return C.union_all([
        row("dearest", t.part.agg(F.max("p_retailprice"))),
        row("urgent minus low", o.agg((F.count_if(F.col("o_orderpriority") == "1-URGENT") - F.count_if(F.col("o_orderpriority") == "5-LOW")).alias("v"))),
        row("over 300000", o.where("o_totalprice > 300000").agg(F.count("*"))), row("after key 10", o.where("o_orderkey > 10").agg(F.min("o_orderkey"))), row("nations of first region", t.nation.where("n_regionkey = 0").agg(F.count("*"))),
    ])


# --- verification and text ---------------------------------------------------


W10_SQL = f"""WITH s AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1), c AS (SELECT o_custkey, n, n + CASE WHEN {det.sql_unit("'lie'", 'o_custkey')} < 0.5 THEN 1 ELSE 0 END AS said, {det.sql_unit("'lie'", 'o_custkey')} >= 0.5 AS truth FROM s)
SELECT said = n AS verdict, count(*)::BIGINT AS n, round(avg(((said = n) = truth)::INT), 6) AS accuracy FROM c GROUP BY 1"""


@query("w10", W10_SQL)
def w10(t):
    """Statements on numbers of orders, half of them changed by one, checked against the table."""
    s = t.orders.groupBy("o_custkey").agg(F.count("*").alias("k"))
    lie = det.unit("lie", F.col("o_custkey")) < 0.5
    said = F.col("k") + F.when(lie, 1).otherwise(0)
    c = s.select((said == F.col("k")).alias("verdict"), (~lie).alias("truth"))
    return c.groupBy("verdict").agg(F.count("*").alias("n"), F.round(F.avg((F.col("verdict") == F.col("truth")).cast("int")), 6).alias("accuracy"))


@query("w11", f"SELECT CASE WHEN l.doc_id IS NULL THEN 'undecidable' WHEN l.toxic = ({det.sql_unit(chr(39) + 'claim' + chr(39), 'd.doc_id')} < 0.3)::INT THEN 'supported' ELSE 'refuted' END AS verdict, count(*)::BIGINT AS n FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1")
def w11(t):
    """Claims that a document is harmful or not, with its label as evidence; without one they cannot be decided."""
    claim = (det.unit("claim", F.col("doc_id")) < 0.3).cast("int")
    v = F.when(F.col("toxic").isNull(), "undecidable").when(F.col("toxic") == claim, "supported").otherwise("refuted")
    return t.documents.join(t.labels, "doc_id", "left").groupBy(v.alias("verdict")).agg(F.count("*").alias("n"))


@query("w12", bleu_sql(CUSTOMER_PAIRS))
def w12(t):
    """Sentences from highlighted customer cells."""
    return M.bleu(sentence_pairs(t))


# --- questions to SQL --------------------------------------------------------


# (id, tables, question, reference); the grammar reads a name without its table, so 'per name' is a trap.
PLAIN = [
    ("segment", ["orders", "customer", "nation"], "What is the total totalprice per mktsegment?", "SELECT c_mktsegment, round(sum(o_totalprice), 2) AS answer FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY c_mktsegment"),
    ("trap", ["customer", "nation"], "What is the average acctbal per name?", "SELECT n_name, round(avg(c_acctbal), 2) AS answer FROM nation JOIN customer ON c_nationkey = n_nationkey GROUP BY n_name"),
    ("priority", ["orders"], "How many rows are there per orderpriority?", "SELECT o_orderpriority, count(*) AS answer FROM orders GROUP BY o_orderpriority"),
    ("brand", ["part"], "What is the largest retailprice per brand?", "SELECT p_brand, round(max(p_retailprice), 2) AS answer FROM part GROUP BY p_brand"),
    ("status", ["lineitem", "orders"], "What is the smallest quantity per orderstatus?", "SELECT o_orderstatus, round(min(l_quantity), 2) AS answer FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderstatus"),
    ("discount", ["lineitem", "part"], "What is the largest discount per brand?", "SELECT p_brand, round(max(l_discount), 2) AS answer FROM part JOIN lineitem ON l_partkey = p_partkey GROUP BY p_brand"),
]
KNOWING = [
    ("revenue", ["lineitem", "orders", "customer"], "What is the total revenue per mktsegment?", "SELECT c_mktsegment, round(sum(l_extendedprice * (1 - l_discount)), 2) AS answer FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"),
    ("returned", ["lineitem", "part"], "How many returned rows per brand?", "SELECT p_brand, count(*) AS answer FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_returnflag = 'R' GROUP BY p_brand"),
    ("charge", ["lineitem", "orders"], "What is the largest charge per orderpriority?", "SELECT o_orderpriority, round(max(l_extendedprice * (1 - l_discount) * (1 + l_tax)), 2) AS answer FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority"),
    ("urgent", ["orders", "customer"], "How many urgent rows per mktsegment?", "SELECT c_mktsegment, count(*) AS answer FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_orderpriority = '1-URGENT' GROUP BY c_mktsegment"),
    ("indebted", ["orders", "customer", "nation"], "What is the largest totalprice of indebted rows per regionkey?", "SELECT n_regionkey, round(max(o_totalprice), 2) AS answer FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE c_acctbal < 0 GROUP BY n_regionkey"),
    ("known", ["orders"], "How many rows are there per orderstatus?", "SELECT o_orderstatus, count(*) AS answer FROM orders GROUP BY o_orderstatus"),
]
_FROM = {
    ("orders", "orders"): "orders", ("orders", "customer"): "orders JOIN customer ON o_custkey = c_custkey", ("orders", "nation"): "orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
    ("customer", "orders"): "orders JOIN customer ON o_custkey = c_custkey", ("customer", "customer"): "customer", ("customer", "nation"): "customer JOIN nation ON c_nationkey = n_nationkey",
    ("lineitem", "part"): "lineitem JOIN part ON l_partkey = p_partkey", ("lineitem", "lineitem"): "lineitem", ("part", "part"): "part", ("part", "lineitem"): "lineitem JOIN part ON l_partkey = p_partkey", ("events", "events"): "events",
}


def _split(tables, measures, groups):
    """Questions of every measure by every group that the tables' keys join, for the largest and the smallest value."""
    bare = lambda c: " ".join(A.words_of(c.split("_", 1)[1] if "_" in c else c))
    return [(f"{word}-{m}-{g}", [mt, *[x for x in tables if x != mt]], f"What is the {word} {bare(m)} per {bare(g)}?", f"SELECT {g}, round({fn}({m}), 2) AS answer FROM {_FROM[mt, gt]} GROUP BY {g}") for mt, m in measures for gt, g in groups if (mt, gt) in _FROM for word, fn in (("largest", "max"), ("smallest", "min"))]


DEV = _split(["orders", "customer", "nation"], [("orders", "o_totalprice"), ("customer", "c_acctbal")], [("orders", "o_orderstatus"), ("orders", "o_orderpriority"), ("customer", "c_mktsegment"), ("nation", "n_regionkey")])
TEST = _split(["part", "supplier", "lineitem", "events"], [("lineitem", "l_quantity"), ("part", "p_retailprice"), ("events", "value")], [("part", "p_brand"), ("lineitem", "l_returnflag"), ("lineitem", "l_linestatus"), ("events", "event_type")])
NL2SQL = [("w13", "plain", PLAIN, (True,)), ("w14", "with_knowledge", KNOWING, (False, True)), ("w15", "dev", DEV, (True,)), ("w16", "test", TEST, (True,))]


def _composed(questions, known):
    return [A.compose(q, tables, A.TERMS if known else {}) for _, tables, q, _ in questions]


def _nl2sql_sql(split, questions, ways):
    """Both statements of every question in DuckDB; their results as bags of rows."""
    equal = lambda gold, pred: f"(NOT EXISTS ((({gold}) EXCEPT ALL ({pred})) UNION ALL (({pred}) EXCEPT ALL ({gold}))))::INT"
    fits = lambda gold, pred: "0" if pred.split(" FROM ")[0].count(",") != gold.split(" FROM ")[0].count(",") else equal(gold, pred)
    return " UNION ALL ".join(f"SELECT '{split}' AS split, {known} AS knowledge, {len(questions)}::BIGINT AS samples, round(({' + '.join(fits(q[3], p) for q, p in zip(questions, _composed(questions, known)))}) / {len(questions)}.0, 6)::DOUBLE AS exec_acc" for known in ways)


for _w, _split_name, _questions, _ways in NL2SQL:

    @query(_w, _nl2sql_sql(_split_name, _questions, _ways))
    def w_nl2sql(t, split=_split_name, questions=_questions, ways=_ways):
        """The grammar's statement over joined tables against the reference, both run; with and without the knowledge table where it matters."""
        tables = sorted({x for q in questions for x in q[1]} | ({"customer"} if split == "test" else set()))
        statements = [(f"{q[0]}/gold", q[3]) for q in questions] + [(f"{q[0]}/{known}", p) for known in ways for q, p in zip(questions, _composed(questions, known))]
        runs = X.run_sql(t.spark, statements, {n: getattr(t, n) for n in tables}).withColumn("q", F.split("sample_id", "/")[0]).withColumn("side", F.split("sample_id", "/")[1])
        both = runs.where("side = 'gold'").select("q", F.col("rows_hash").alias("g")).join(runs.where("side <> 'gold'"), "q")
        right = (F.col("g") == F.col("rows_hash")) & (F.col("status") == "ok")
        return both.groupBy((F.col("side") == "True").alias("knowledge")).agg(F.lit(split).alias("split"), F.count("*").alias("samples"), F.round(F.avg(right.cast("int")), 6).alias("exec_acc")).select("split", "knowledge", "samples", "exec_acc")


def _answers(t, mode):
    n, p = F.col("p_size").cast("string"), F.col("p_retailprice").cast("string")
    total = F.format_string("%.2f", F.round(F.col("p_size") * F.col("p_retailprice"), 2))
    gold = F.concat(F.lit("the total is "), total)
    steps = {"direct": F.lit(""), "textual": F.concat(F.lit("multiply the size by the price then "), F.lit("")), "symbolic": F.concat(n, F.lit(" * "), p, F.lit(" = "))}[mode]
    ok = det.unit("wrong", F.col("p_partkey")) >= 0.2
    pred = F.concat(steps, F.lit("the total is "), F.when(ok, total).otherwise("unknown"))
    return t.part.select(F.col("p_partkey").alias("sample_id"), F.split(gold, " ").alias("gold"), F.split(pred, " ").alias("pred"))


for _w, _mode in (("w17", "direct"), ("w18", "textual"), ("w19", "symbolic")):

    @query(_w)
    def w_rouge(t, mode=_mode):
        return M.rouge_l(_answers(t, mode)).select(F.lit(mode).alias("mode"), "samples", "rouge_l")


W20_SQL = f"""WITH p AS (SELECT s_nationkey AS problem, unnest(range(4)) AS i FROM (SELECT DISTINCT s_nationkey FROM supplier)), r AS (SELECT problem, i, {det.sql_pick(4, "'try'", 'problem', 'i')} = 0 AS ok FROM p),
c AS (SELECT problem % 2 AS kind, problem, count(*) AS n, count(*) FILTER (WHERE ok) AS c FROM r GROUP BY ALL) SELECT CASE kind WHEN 0 THEN 'number' ELSE 'chart' END AS kind, 1 AS k, count(*)::BIGINT AS problems, round(avg(c::DOUBLE / n), 6) AS pass_at_k FROM c GROUP BY ALL"""


def programs(t):
    """(problem, i, kind, code, gold): four tries at a program on each nation's suppliers, three in four of them with some fault.

    Even nations ask for a number, odd ones for a chart, which is checked through its series.
    """
    g = t.supplier.groupBy(F.col("s_nationkey").alias("problem")).agg(F.transform(F.array_sort(F.collect_list(F.struct("s_suppkey", "s_acctbal"))), lambda x: x["s_acctbal"]).alias("xs"))
    data = F.concat(F.lit("rows = ["), F.array_join(F.transform("xs", lambda x: F.concat(F.lit("{'balance': "), F.format_string("%.2f", x), F.lit("}"))), ", "), F.lit("]\n"))
    kind = F.when(F.col("problem") % 2 == 0, "number").otherwise("chart")
    number = ["print(round(max(r['balance'] for r in rows), 2))", "print(round(max(r['saldo'] for r in rows), 2))", "print(round(max(r['balance'] for r in rows, 2))", "print(round(min(r['balance'] for r in rows) - 1, 2))"]
    chart = ["print([round(r['balance'], 2) for r in rows])", "print([round(r['saldo'], 2) for r in rows])", "print([round(r['balance'], 2) for r in rows)", "print([round(r['balance'] + 1, 2) for r in rows])"]
    tries = g.select("problem", kind.alias("kind"), data.alias("data"), F.round(F.array_max("xs"), 2).alias("most"), F.transform("xs", lambda x: F.round(x, 2)).alias("series"), F.explode(F.sequence(F.lit(0), F.lit(3))).alias("i"))
    fault = det.pick(4, "try", F.col("problem"), F.col("i"))
    body = F.when(F.col("kind") == "number", F.get(F.array(*map(F.lit, number)), fault)).otherwise(F.get(F.array(*map(F.lit, chart)), fault))
    return tries.select("problem", "i", "kind", F.concat("data", body).alias("code"), "most", "series")


@query("w20", W20_SQL)
def w20(t):
    """The programs are run; an output counts if it holds the number, or the series, that the table gives."""
    made = cut(programs(t).withColumn("sample_id", F.concat_ws("/", F.col("problem").cast("string"), F.col("i").cast("string"))))
    runs = X.run_python(made.select("sample_id", "code").repartition(t.spark.sparkContext.defaultParallelism), seconds=5)
    both = made.join(runs, "sample_id")
    number = F.abs(F.trim("output").try_cast("double") - F.col("most")) < 0.005
    seen = F.from_json("output", "array<double>")
    series = (F.size(seen) == F.size("series")) & F.forall(F.zip_with(seen, "series", lambda a, b: F.abs(a - b)), lambda d: d < 0.005)
    ok = (F.col("status") == "ok") & F.coalesce(F.when(F.col("kind") == "number", number).otherwise(series), F.lit(False))
    judged = cut(both.select("kind", "problem", ok.alias("ok")))
    return C.union_all([M.pass_at_k(judged.where(F.col("kind") == k), 1).select(F.lit(k).alias("kind"), "k", "problems", "pass_at_k") for k in ("number", "chart")])


# --- judged slices -----------------------------------------------------------


def _slice_sql(name, pred):
    return JUDGE_SQL.replace("CASE WHEN c_custkey % 3 = 0 THEN c_name || ' balance unknown' WHEN c_custkey % 50 = 1 THEN 'drop table customer' ELSE c_name || ' balance ' || c_acctbal END AS pred", f"{pred} AS pred") + f" SELECT '{name}' AS slice, round(avg(consistency), 4) AS consistency, round(avg(completeness), 4) AS completeness, round(avg(security), 4) AS security, round(avg((consistency + completeness + security) / 3), 3) AS total FROM s"


def _judged(t, name, pred):
    bal = F.col("c_acctbal").cast("string")
    rows = t.customer.select(F.col("c_custkey").alias("sample_id"), pred.alias("pred"), F.concat("c_name", F.lit(" balance "), bal).alias("gold"), F.array("c_name", bal).alias("facts"))
    s = M.judge(rows)
    return s.agg(F.lit(name).alias("slice"), *[F.round(F.avg(c), 4).alias(c) for c in ("consistency", "completeness", "security")], F.round(F.avg((F.col("consistency") + F.col("completeness") + F.col("security")) / 3), 3).alias("total"))


@query("w21", _slice_sql("general", "c_name || ' balance ' || c_acctbal"))
def w21(t):
    return _judged(t, "general", F.concat("c_name", F.lit(" balance "), F.col("c_acctbal").cast("string")))


def _scored(rows, *by):
    means = [F.round(F.avg(c), 4).alias(c) for c in ("consistency", "completeness", "security")]
    return M.judge(rows).join(rows.select("sample_id", *by), "sample_id").groupBy(*by).agg(F.count("*").alias("samples"), *means, F.round(F.avg((F.col("consistency") + F.col("completeness") + F.col("security")) / 3), 3).alias("total"))


@query("w22")
def w22(t):
    """Questions on a merged-header table. Read as it stands, a column is found by its region only; normalised, by region and nation."""
    g = cut(table_plans.grid(t))
    years = g.where("not is_header and c = 0").select("r", F.col("value").alias("year"))
    flat = T.replay(g, T.plan_of(g))
    named = flat.where("col_id > 0").join(years, F.col("row_id") == F.col("r")).select(F.col("col_name").alias("asked"), "year", "value")
    tops = g.where("is_header and r = 0 and c > 0").select(F.col("value").alias("region"), "c")
    raw = g.where("not is_header").join(tops, "c").join(years, "r").select("region", "year", F.col("value").alias("raw"))
    gold = w05(t).select(F.col("question_id").alias("asked"), "region", F.col("year").cast("string").alias("year"), F.col("gold").cast("string").alias("gold"))
    both = gold.join(named, ["asked", "year"]).join(raw, ["region", "year"], "left")
    text = lambda v: F.concat_ws(" ", F.col("asked"), F.col("year"), v)
    rows = lambda way, v: both.select(F.concat_ws("|", F.lit(way), "asked", "year").alias("sample_id"), F.lit(way).alias("way"), text(v).alias("pred"), text(F.col("gold")).alias("gold"), F.array("gold").alias("facts"))
    return _scored(cut(rows("raw", F.coalesce("raw", F.lit("unknown"))).unionByName(rows("normalised", F.col("value")))), "way").select(F.lit("irregular").alias("slice"), "*")


@query("w23")
def w23(t):
    """'Which rows perform best' under anonymised headers: taken by the first measure at hand, or asked back and answered by the measure's name."""
    cells, mapping = T.anonymise(star_cells(t, ("customer", "supplier", "part", "orders")))
    best = cells.groupBy("table_id", F.col("col_name").alias("new")).agg(F.max(F.col("value").try_cast("double")).alias("best"), F.bool_and(T.kind(F.col("value")) == "double").alias("measure"))
    heads = mapping.where("kind = 'header'").select("table_id", "old", "new")
    known = cut(heads.join(best, ["table_id", "new"]))
    meant = X.columns_frame(t.spark).where("kind = 'number'").select("table_id", F.col("col").alias("old")).join(known, ["table_id", "old"])
    first = known.where("measure").groupBy("table_id").agg(F.min_by("best", "new").alias("guess"))
    both = meant.join(first, "table_id", "left")
    text = lambda v: F.concat_ws(" ", F.lit("best"), F.col("table_id"), F.format_string("%.2f", v))
    rows = lambda way, v: both.select(F.concat_ws("|", F.lit(way), "table_id", "old").alias("sample_id"), F.lit(way).alias("way"), text(v).alias("pred"), text(F.col("best")).alias("gold"), F.array(F.format_string("%.2f", "best")).alias("facts"))
    return _scored(cut(rows("guessed", F.col("guess")).unionByName(rows("asked_back", F.col("best")))), "way").select(F.lit("ambiguous").alias("slice"), "*")


# --- general ability, boards, builds -----------------------------------------


@query("w24")
def w24(t):
    """Small programs with a test each, run in child processes."""
    tasks = [("add", "def f(a, b):\n    return a + b\nassert f(2, 3) == 5"), ("rev", "def f(s):\n    return s[::-1]\nassert f('abc') == 'cba'"), ("bad", "def f(a):\n    return a\nassert f(1) == 2"), ("fib", "def f(n):\n    return n if n < 2 else f(n - 1) + f(n - 2)\nassert f(10) == 55")]
    return solved(X.run_python(t.spark.createDataFrame([(n, c) for n, c in tasks], "sample_id string, code string").repartition(2)), "small_programs")


def solved(runs, name):
    return runs.agg(F.lit(name).alias("set"), F.count_if(F.col("status") == "ok").alias("solved"), F.count("*").alias("total"))


@query("w24_tables", "SELECT 'table_programs' AS \"set\", count(*) FILTER (WHERE block % 3 < 2 OR hi = lo)::BIGINT AS solved, count(*)::BIGINT AS total FROM (SELECT p_partkey // 200 AS block, max(p_size) AS hi, min(p_size) AS lo FROM part GROUP BY 1)")
def w24_tables(t):
    """A program for every block of 200 part keys over their sizes, tested on what Spark finds: sums and largest sizes are asked for, and a third of the programs answers with the smallest instead."""
    block = F.expr("p_partkey div 200")
    g = t.part.groupBy(block.alias("block")).agg(F.array_sort(F.collect_list("p_size")).alias("sizes"), F.sum("p_size").alias("sum"), F.max("p_size").alias("max"))
    kind = F.col("block") % 3
    done = F.when(kind == 0, "sum").when(kind == 1, "max").otherwise("min")
    want = F.when(kind == 0, F.col("sum")).otherwise(F.col("max"))
    code = F.concat(F.lit("def f(rows):\n    return "), done, F.lit("(rows)\nassert f(["), F.array_join(F.col("sizes").cast("array<string>"), ", "), F.lit("]) == "), want.cast("string"))
    return solved(X.run_python(g.select(F.col("block").cast("string").alias("sample_id"), code.alias("code"))), "table_programs")


@query("w25")
def w25(t):
    """Four options for the language of a document; the function-word scores choose."""
    s = t.documents.select("lang", *[F.coalesce(c, F.lit(0.0)).alias(k) for k, c in C.language_scores(F.col("text")).items()])
    best = F.greatest("de", "en", "es", "fr")
    pred = F.when(F.col("de") == best, "de").when(F.col("en") == best, "en").when(F.col("es") == best, "es").otherwise("fr")
    return s.agg(F.lit("language").alias("set"), F.round(F.avg((pred == F.col("lang")).cast("int")), 6).alias("accuracy"))


W25_PASSAGE_SQL = """
WITH w AS (SELECT doc_id, string_split(lower(text), ' ') AS words FROM documents WHERE text IS NOT NULL),
h AS (SELECT doc_id, list_distinct(words[1:len(words) // 2]) AS head, list_distinct(words[len(words) // 2 + 1:len(words)]) AS tail FROM w),
o AS (SELECT q.doc_id, k, len(list_intersect(q.head, a.tail)) * 1000 // len(a.tail) AS score FROM h a, (VALUES (0), (1), (2), (3)) v(k) JOIN h q ON q.doc_id = a.doc_id - k),
r AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY score DESC, k DESC) AS r FROM o)
SELECT 'passage' AS "set", sum((k = 0)::INT)::BIGINT AS correct, count(*)::BIGINT AS total, round(avg((k = 0)::INT), 6) AS accuracy FROM r WHERE r = 1"""


@query("w25_passage", W25_PASSAGE_SQL)
def w25_passage(t):
    """Which of four passages goes on from the first half of a document: its own second half or that of one of the three next ids.

    The passage with the largest share of its words in the first half is chosen; ties count against the method.
    Only word hashes are shuffled.
    """
    words = t.documents.where("text IS NOT NULL").select("doc_id", F.split(F.lower("text"), " ").alias("words")).withColumn("half", F.expr("cast(size(words) div 2 AS int)"))
    hashed = lambda a: F.transform(F.array_distinct(a), lambda x: F.xxhash64(x))
    heads = words.select("doc_id", hashed(F.slice("words", 1, F.col("half"))).alias("head"))
    tails = words.select(F.col("doc_id").alias("own"), hashed(F.slice("words", F.col("half") + 1, F.size("words"))).alias("tail"))
    options = tails.select("own", "tail", F.explode(F.array(*map(F.lit, range(4)))).alias("k")).select((F.col("own") - F.col("k")).alias("doc_id"), "k", "tail")
    score = F.expr("size(array_intersect(head, tail)) * 1000 div size(tail)")
    chosen = heads.join(options, "doc_id").groupBy("doc_id").agg(F.max(F.struct(score.alias("score"), "k")).alias("best"))
    hit = (F.col("best.k") == 0).cast("int")
    return chosen.agg(F.lit("passage").alias("set"), F.sum(hit).alias("correct"), F.count("*").alias("total"), F.round(F.avg(hit), 6).alias("accuracy"))


@query("w26", SCORES_SQL + f", g AS ({_gain_sql('P7', '(5, 6)')}), m AS (SELECT system, round(avg(value), 4) AS mean_score, count(*)::BIGINT AS n_rows FROM s WHERE table_no IN (5, 6) GROUP BY 1) SELECT m.system, mean_score, m.n_rows, g.gain AS improvement FROM m LEFT JOIN g USING (system)")
def w26(t):
    s = M.scores_frame(t.spark)
    mean = s.where("table_no in (5, 6)").groupBy("system").agg(F.round(F.avg("value"), 4).alias("mean_score"), F.count("*").alias("n_rows"))
    return mean.join(M.improvement(s, "P7", [5, 6]).select("system", F.col("gain").alias("improvement")), "system", "left")


# Shares of the kinds in the corpus, most of it code.
KIND_SHARES = {"code_python": 0.512, "code_sql": 0.128, "text_en": 0.16, "text_other": 0.2}


def without_repeats(docs):
    """``docs`` (doc_id, text, ...) whose repeated lines stay in their first document only."""
    rows = docs.select("doc_id", F.posexplode(lines(F.col("text"))).alias("pos", "line")).withColumn("line_hash", F.md5("line"))
    gone = rows.join(C.repeated_lines(docs), "line_hash", "left").where("first_doc is null or first_doc = doc_id")
    text = gone.groupBy("doc_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "line"))), lambda x: x["line"]), "\n").alias("text"))
    return docs.drop("text").join(text, "doc_id")


@query("w27")
def w27(t):
    """Corpus build in one chain: text and code joined, copies, near copies and repeated lines out, filters, test passages out, tokens selected, kinds mixed, packs made."""
    n = F.size(F.regexp_extract_all("text", F.lit(r"\S+"), F.lit(0))).cast("long")
    prose = t.documents.select("doc_id", "text", F.when(F.col("lang") == "en", "text_en").otherwise("text_other").alias("kind"))
    code = samples.code_samples(t.orders).where("ok").select((F.lit(1 << 40) + F.col("code_id")).alias("doc_id"), "text", F.concat(F.lit("code_"), "lang").alias("kind"))
    every = cut(prose.unionByName(code))
    first = cut(every.join(C.exact(every).select("doc_id"), "doc_id", "left_semi"))
    single = cut(first.join(C.near_groups(first).where("doc_id = class_id").select("doc_id"), "doc_id", "left_semi"))
    fresh = cut(without_repeats(single))
    held = C.decide(fresh.where("kind like 'text%'")).where("not keep").select("doc_id")
    kept = cut(fresh.join(held, "doc_id", "left_anti"))
    clean = cut(kept.join(C.decontaminate(kept, t.benchmark), "doc_id", "left_anti").withColumn("n", n).where("n > 0"))
    loss = C.selective_loss(C.masked(C.excess(clean, t.labels)))
    mixed = cut(C.to_ratio(clean, "kind", "n", KIND_SHARES, "doc_id"))
    packs = C.by_length(mixed, 512)
    count = lambda i, name, df: df.agg(F.lit(i).alias("step"), F.lit(name).alias("stage"), F.count("*").alias("docs"), F.coalesce(F.sum(n), F.lit(0)).alias("tokens"))
    out = [count(i, name, df) for i, (name, df) in enumerate([("all", every), ("exact", first), ("near", single), ("lines", fresh), ("filtered", kept), ("neutral", clean)])]
    out.append(loss.agg(F.lit(6).alias("step"), F.lit("selected").alias("stage"), F.count("*").alias("docs"), F.coalesce(F.sum("n_kept"), F.lit(0)).alias("tokens")))
    out.append(count(7, "mixed", mixed))
    out.append(packs.agg(F.lit(8).alias("step"), F.lit("packed").alias("stage"), F.countDistinct("doc_id").alias("docs"), F.coalesce(F.sum(F.col("to") - F.col("from")), F.lit(0)).alias("tokens")))
    return C.union_all(out)


@query("w27_dedup_contrast", f"SELECT 'none' AS way, count(*)::BIGINT AS docs, sum(len({TOK}))::BIGINT AS tokens FROM documents UNION ALL SELECT 'exact', count(*), sum(len({TOK}))::BIGINT FROM documents WHERE doc_id IN (SELECT min(doc_id) FROM documents GROUP BY md5(text)) UNION ALL SELECT 'near', count(*), sum(len({TOK}))::BIGINT FROM documents WHERE doc_id IN (SELECT class_id FROM ({NEAR_SQL}))")
def w27_dedup_contrast(t):
    n = F.size(F.regexp_extract_all("text", F.lit(r"\S+"), F.lit(0))).cast("long")
    first = t.documents.join(C.exact(t.documents).select("doc_id"), "doc_id", "left_semi")
    near = t.documents.join(C.near_groups(t.documents).where("doc_id = class_id").select("doc_id"), "doc_id", "left_semi")
    return C.union_all([df.agg(F.lit(k).alias("way"), F.count("*").alias("docs"), F.sum(n).alias("tokens")) for k, df in (("none", t.documents), ("exact", first), ("near", near))])


@query("w28")
def w28(t):
    """Contrastive loss of pooled customer columns by nation at two temperatures; and with both samples from the same rows."""
    cells = E.embed(encoder_plans.snapshot_cells(t))
    tagged = cells.withColumn("table_id", F.concat_ws("#", "table_id", F.col("snap").cast("string")))
    vecs = E.pool(tagged).select(F.split("table_id", "#")[0].alias("table_id"), F.split("table_id", "#")[1].cast("int").alias("snap"), "col_id", "vec")
    vecs = cut(E.batches(vecs, 256))
    same = vecs.where("snap = 0").unionByName(vecs.where("snap = 0").withColumn("snap", F.lit(1)))
    out = [E.contrast_loss(vecs, tau).agg(F.lit("two_samples").alias("way"), F.lit(tau).alias("tau"), F.round(F.avg("loss"), 4).alias("loss")) for tau in (0.07, 0.5)]
    return C.union_all([*out, E.contrast_loss(same, 0.07).agg(F.lit("same_rows").alias("way"), F.lit(0.07).alias("tau"), F.round(F.avg("loss"), 4).alias("loss"))])


@query("w29")
def w29(t):
    """Sample factory from questions to training samples, single- and two-turn."""
    stages = X.staged(X.drafts(X.questions(t.spark)), {n: getattr(t, n) for n in X.SEMANTIC})
    return M.funnel([*stages, ("combined", X.combine_turns(stages[-1][1]))])


W30_SQL = """WITH d AS (SELECT o_orderdate AS day FROM orders GROUP BY 1 ORDER BY count(*) DESC, o_orderdate LIMIT 1), o AS (SELECT o.* FROM orders o JOIN d ON o_orderdate = day), l AS (SELECT l.* FROM lineitem l SEMI JOIN o ON l_orderkey = o_orderkey)
SELECT 0 AS turn, 'count' AS question, count(*)::DOUBLE AS answer FROM o UNION ALL SELECT 1, 'total', round(sum(o_totalprice), 2) FROM o UNION ALL SELECT 2, 'mean tax', round(avg(l_tax), 6) FROM l"""


@query("w30", W30_SQL)
def w30(t):
    """Three chained questions on the busiest day: the filter of the first is carried on."""
    day = t.orders.groupBy("o_orderdate").count().orderBy(F.desc("count"), "o_orderdate").limit(1).select("o_orderdate")
    o = t.orders.join(F.broadcast(day), "o_orderdate", "left_semi")
    tax = t.lineitem.join(o, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").agg(F.round(F.avg("l_tax"), 6).alias("v"))
    row = lambda i, q, df: df.select(F.lit(i).alias("turn"), F.lit(q).alias("question"), F.col(df.columns[0]).cast("double").alias("answer"))
    return C.union_all([row(0, "count", o.agg(F.count("*"))), row(1, "total", o.agg(F.round(F.sum("o_totalprice"), 2))), row(2, "mean tax", tax)])


W31_SQL = """WITH s AS (SELECT l_partkey AS k, sum(l_quantity) AS q, round(sum(l_extendedprice * (1 - l_discount)), 2) AS r FROM lineitem GROUP BY 1)
SELECT * FROM (SELECT 'quantity' AS metric, k AS p_partkey, q AS value FROM s ORDER BY q DESC, k LIMIT 1) UNION ALL SELECT * FROM (SELECT 'revenue', k, r FROM s ORDER BY r DESC, k LIMIT 1) UNION ALL SELECT * FROM (SELECT 'price', p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 1)"""


@query("w31", W31_SQL)
def w31(t):
    """The best product by each measure that 'best' may mean."""
    s = t.lineitem.groupBy(F.col("l_partkey").alias("p_partkey")).agg(F.sum("l_quantity").alias("quantity"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))
    top = lambda m, df: df.select(F.lit(m).alias("metric"), "p_partkey", F.col(m if m != "price" else "p_retailprice").alias("value")).orderBy(F.desc("value"), "p_partkey").limit(1)
    return C.union_all([top("quantity", s), top("revenue", s), top("price", t.part)])


@query("w32")
def w32(t):
    """Retrieval, then a statement over the table found, then its run."""
    docs = A.schema_docs(t.spark)
    ranked = A.rerank(A.embed_search(agent_plans.asked(t), docs), agent_plans.asked(t), docs).join(docs.select("item_id", "table_id"), "item_id")
    best = {r.query_id: r.table_id for r in ranked.where("rank = 1").collect()}
    texts = {a: b for a, b, _ in agent_plans.ASKED}
    samples = [(q, A.generate(texts[q], [tab], "hint")) for q, tab in sorted(best.items())]
    runs = X.run_sql(t.spark, samples, {n: getattr(t, n) for n in set(best.values())})
    tabs = t.spark.createDataFrame(sorted(best.items()), "sample_id string, tables string")
    return runs.join(tabs, "sample_id").select(F.col("sample_id").alias("question_id"), "tables", "status", F.col("n_rows").alias("rows"))


@query("w33", "WITH d AS (SELECT event_type, ts::DATE AS day, avg(value) AS v FROM events GROUP BY 1, 2), m AS (SELECT event_type, avg(v) AS m FROM d GROUP BY 1) SELECT strftime(day, '%Y-%m-%d') AS day, event_type AS intent, round(v, 8) AS value, CASE WHEN v > m THEN 'above' ELSE 'below' END AS note FROM d JOIN m USING (event_type)")
def w33(t):
    return agent_plans.agt_dag(t).select("day", F.col("event_type").alias("intent"), "value", "note")


@query("w34")
def w34(t):
    """One sample of each slice, before and after normalising."""
    g = table_plans.grid(t)
    irregular = T.flatten_headers(T.unmerge(g)).agg(F.min("col_name").alias("after")).select(F.lit("irregular").alias("slice"), F.lit("merged header").alias("before"), "after")
    general = t.nation.agg(F.min("n_name").alias("before")).select(F.lit("general").alias("slice"), "before", F.col("before").alias("after"))
    cells = table_plans.small_cells(t)
    anon = T.anonymise(cells)[1].where("kind = 'header'").agg(F.min_by("old", "new").alias("before"), F.min("new").alias("after")).select(F.lit("ambiguous").alias("slice"), "before", "after")
    return C.union_all([general, irregular, anon])


@query("x_permutation_contrast")
def x_permutation_contrast(t):
    """Largest change of column vectors when rows are shuffled: none without positions, some with them."""
    import numpy as np

    cells = E.embed(encoder_plans.snapshot_cells(t, 8)).where("table_id = '0' and snap = 0").toPandas()  # one sampled table of 8 rows
    e, _, _ = E.grid_of(cells)
    order = np.random.default_rng(1).permutation(len(e))
    w = E.adapter_weights(E.D)

    def columns(x, positions):
        out = E.encode_grid(x, 2, positions=positions)
        return np.stack([(lambda s: s[2] / s[1][:, None])(E.adapter_state(out[:, j], w)) for j in range(out.shape[1])])

    rows = [(p, bool(np.abs(columns(e, p) - columns(e[order], p)).max() > 1e-6)) for p in (False, True)]
    return t.spark.createDataFrame(rows, "positions boolean, changed boolean")
