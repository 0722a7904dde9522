"""Agent runtime: two-stage retrieval, prompt preparation, bounded retry, sandbox expiry, chart facts, a small DSL and a DAG of steps.

The generating model is stood in by a frame grammar over the catalogue; every
step exchanges DataFrames, so a model can take its place.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tablemill.functions.lineage import cut
from tablemill.functions.text import ngrams, tokens
from tablemill.operators.factory import KEY_OF, SEMANTIC, error_class, run_sql

# --- retrieval ---------------------------------------------------------------


def words(text: Column) -> Column:
    """Lower-case letters and digits; identifiers are cut at underscores."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit("[a-z0-9]+"), F.lit(0))


def grams(text: Column) -> Column:
    """Word and letter-trigram features of a text."""
    return F.flatten(F.transform(words(text), lambda w: F.concat(F.array(w), F.transform(F.sequence(F.lit(1), F.greatest(F.length(w) - 2, F.lit(1))), lambda i: F.concat(F.lit("#"), F.substr(w, i, F.lit(3)))))))


def vector(df: DataFrame, key: str, text: str) -> DataFrame:
    """(key, g, x): unit vectors in sparse long form, log counts as weights."""
    c = df.select(key, F.explode(grams(F.col(text))).alias("g")).groupBy(key, "g").agg((1 + F.log(F.count("*"))).alias("x"))
    n = c.groupBy(key).agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("n"))
    return c.join(n, key).select(key, "g", (F.col("x") / F.col("n")).alias("x"))


def embed_search(queries: DataFrame, docs: DataFrame, k: int = 20) -> DataFrame:
    """(query_id, item_id, score, rank): cosine over features that both sides hold; only those are joined."""
    q, d = vector(queries, "query_id", "query"), vector(docs, "item_id", "text").withColumnRenamed("x", "y")
    s = q.join(d, "g").groupBy("query_id", "item_id").agg(F.round(F.sum(F.col("x") * F.col("y")), 6).alias("score"))
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "item_id")
    return s.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def rerank(cands: DataFrame, queries: DataFrame, docs: DataFrame, k: int = 5, k1: float = 1.2, b: float = 0.75) -> DataFrame:
    """BM25 of the candidates' texts plus half a point for each query word in the item's name; best k."""
    terms = docs.select("item_id", F.explode(words(F.col("text"))).alias("w"))
    tf = terms.groupBy("item_id", "w").agg(F.count("*").alias("tf"))
    length = terms.groupBy("item_id").agg(F.count("*").alias("len"))
    total = docs.agg(F.count("*").alias("n")).crossJoin(length.agg(F.avg("len").alias("mean")))
    df_ = tf.groupBy("w").agg(F.count("*").alias("df"))
    asked = queries.select("query_id", F.explode(F.array_distinct(words(F.col("query")))).alias("w"))
    both = cands.select("query_id", "item_id").join(asked, "query_id").join(tf, ["item_id", "w"]).join(df_, "w").join(length, "item_id").crossJoin(F.broadcast(total))
    idf = F.log(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    part = idf * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("len") / F.col("mean")))
    bm = both.groupBy("query_id", "item_id").agg(F.sum(part).alias("bm25"))
    named = cands.select("query_id", "item_id").join(docs.select("item_id", words(F.col("name")).alias("nw")), "item_id").join(queries.select("query_id", words(F.col("query")).alias("qw")), "query_id")
    bonus = named.select("query_id", "item_id", (0.5 * F.size(F.array_intersect("nw", "qw"))).alias("bonus"))
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "item_id")
    scored = bonus.join(bm, ["query_id", "item_id"], "left").select("query_id", "item_id", F.round(F.coalesce("bm25", F.lit(0.0)) + F.col("bonus"), 6).alias("score"))
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def schema_docs(spark: SparkSession) -> DataFrame:
    """One item for each table and column of the catalogue."""
    rows = [(t, t, t, f"table {t} with " + " ".join(cs)) for t, cs in SEMANTIC.items()]
    rows += [(f"{t}.{c}", t, c, f"{c} {s} of {t}") for t, cs in SEMANTIC.items() for c, s in cs.items()]
    return spark.createDataFrame(rows, "item_id string, table_id string, name string, text string")


def value_docs(spark: SparkSession, tables: Callable[[str], DataFrame]) -> DataFrame:
    """``schema_docs`` with what the tables hold: all values of a category, the least and greatest of any other column.

    One pass over each table; a category has few values by its meaning, so they travel as one text.
    """
    shown = lambda c, kind: F.array_join(F.array_sort(F.collect_set(F.col(c).cast("string"))), " ") if kind == "category" else F.concat_ws(" to ", F.min(c).cast("string"), F.max(c).cast("string"))
    held = [tables(t).agg(F.array(*[F.struct(F.lit(f"{t}.{c}").alias("item_id"), shown(c, kind).alias("held")) for c, kind in cs.items()]).alias("items")).select(F.inline("items")) for t, cs in SEMANTIC.items()]
    values = held[0]
    for one in held[1:]:
        values = values.unionByName(one)
    return cut(schema_docs(spark).join(values, "item_id", "left").select("item_id", "table_id", "name", F.concat_ws(" ", "text", F.nullif(F.col("held"), F.lit(""))).alias("text")))


PARENTS = [("orders", "customer"), ("lineitem", "orders"), ("lineitem", "part"), ("lineitem", "supplier"), ("customer", "nation"), ("supplier", "nation")]


def schema_of(ranked: DataFrame, docs: DataFrame, spark: SparkSession) -> DataFrame:
    """(query_id, table_id): tables of the ranked items and the parents their keys lead to, so that joins are possible."""
    up = spark.createDataFrame(PARENTS, "table_id string, parent string")
    got = ranked.join(docs.select("item_id", "table_id"), "item_id").select("query_id", "table_id").distinct()
    return got.unionByName(got.join(F.broadcast(up), "table_id").select("query_id", F.col("parent").alias("table_id"))).distinct()


def chunks(docs: DataFrame, size: int = 200, overlap: int = 40) -> DataFrame:
    """(doc_id, pos, text): overlapping runs of words."""
    step = size - overlap
    ws = docs.select("doc_id", tokens(F.col("text")).alias("ws")).where(F.size("ws") > 0)
    starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil((F.size("ws") - overlap) / step).cast("int") - 1))
    return ws.select("doc_id", "ws", F.explode(starts).alias("pos")).select("doc_id", "pos", F.array_join(F.slice("ws", F.col("pos") * step + 1, size), " ").alias("text"))


def knowledge(queries: DataFrame, docs: DataFrame, n: int = 3, k: int = 3) -> DataFrame:
    """(query_id, doc_id, pos, hits, rank): fragments that share most word n-grams with the question."""
    q = queries.select("query_id", F.explode(F.array_distinct(ngrams(tokens(F.lower("query")), n))).alias("g"))
    c = chunks(docs).select("doc_id", "pos", F.explode(F.array_distinct(ngrams(tokens(F.lower("text")), n))).alias("g"))
    hits = c.join(q, "g").groupBy("query_id", "doc_id", "pos").agg(F.count("*").alias("hits"))
    w = Window.partitionBy("query_id").orderBy(F.desc("hits"), "doc_id", "pos")
    return hits.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def within_budget(items: DataFrame, budget: int, order: str = "rank") -> DataFrame:
    """(query_id, item_id, used) of the ranked items of each query whose words, added up in order, stay within the budget.

    Only lengths are ordered and summed; the texts of what stays are joined by the caller.
    """
    sized = items.select("query_id", "item_id", F.col(order).alias("_order"), F.size(tokens(F.col("text"))).alias("_n"))
    w = Window.partitionBy("query_id").orderBy("_order").rowsBetween(Window.unboundedPreceding, 0)
    return sized.withColumn("used", F.sum("_n").over(w)).where(F.col("used") <= budget).select("query_id", "item_id", "used")


INSTRUCTIONS = {
    "role": "You analyse tables for a business.",
    "function": "Answer with one SELECT statement over the listed tables.",
    "usage": "Use the schema items given; ask back when a measure is not named.",
    "limits": "Refuse requests that are not about the data, that ask for secrets, or that would change it.",
}
OFF_TOPIC = r"password|credit card|weather|poem|delete |drop |hack"


def refuse(query: Column) -> Column:
    return F.lower(query).rlike(OFF_TOPIC)


# --- tools -------------------------------------------------------------------


def tools(spark: SparkSession, tables: dict[str, DataFrame]) -> dict[str, Callable[[dict], dict]]:
    """The tools by name; each takes the arguments of a call and returns what it found."""

    def run(arguments):
        r = run_sql(spark, [("call", arguments["sql"])], tables).first()
        return {"status": r.status, "rows": r.n_rows}

    def described(arguments):
        if arguments.get("table") not in SEMANTIC:
            return {"status": "error", "rows": 0}
        return {"status": "ok", "rows": len(SEMANTIC[arguments["table"]])}

    def plotted(arguments):
        known = arguments.get("kind") in ("bar", "line", "scatter") and {arguments.get("x"), arguments.get("y")} <= set(SEMANTIC.get(arguments.get("table"), {}))
        return {"status": "ok" if known else "error", "rows": 0}

    return {"query": run, "describe": described, "plot": plotted}


def dispatch(spark: SparkSession, calls: list[tuple[str, str]], tables: dict[str, DataFrame]) -> DataFrame:
    """(call_id, tool, status, rows) of calls given as JSON; one that cannot be read or names no tool is an error, not a failure."""
    import json

    known, out = tools(spark, tables), []
    for call_id, text in calls:
        try:
            call = json.loads(text)
            tool = str(call["tool"])
            found = known[tool](call["arguments"]) if tool in known else {"status": "unknown_tool", "rows": 0}
        except (ValueError, KeyError, TypeError):
            tool, found = "", {"status": "unreadable", "rows": 0}
        out.append((call_id, tool, found["status"], found["rows"]))
    return spark.createDataFrame(out, "call_id string, tool string, status string, rows long")


# --- statements over joined tables, with outside knowledge -------------------

# Each foreign key: child table, its column, parent table, the parent's key.
KEYS = [
    ("lineitem", "l_orderkey", "orders", "o_orderkey"), ("lineitem", "l_partkey", "part", "p_partkey"), ("lineitem", "l_suppkey", "supplier", "s_suppkey"),
    ("orders", "o_custkey", "customer", "c_custkey"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("supplier", "s_nationkey", "nation", "n_nationkey"),
    ("events", "user_id", "customer", "c_custkey"),
]
# Business terms: what they measure, or which rows they mean, and the table they speak of.
TERMS = {
    "revenue": ("measure", "l_extendedprice * (1 - l_discount)", "lineitem"),
    "charge": ("measure", "l_extendedprice * (1 - l_discount) * (1 + l_tax)", "lineitem"),
    "returned": ("filter", "l_returnflag = 'R'", "lineitem"),
    "urgent": ("filter", "o_orderpriority = '1-URGENT'", "orders"),
    "indebted": ("filter", "c_acctbal < 0", "customer"),
}


def join_path(tables: list[str]) -> list[tuple[str, str]]:
    """(table, condition) steps that join all ``tables`` along their keys, from the first on; tables between them come along."""
    steps, have = [(tables[0], "")], [tables[0]]
    for goal in tables[1:]:
        if goal in have:
            continue
        paths = [[(t, "")] for t in have]
        while paths and paths[0][-1][0] != goal:
            path = paths.pop(0)
            for child, key, parent, unique in KEYS:
                for here, there in ((child, parent), (parent, child)):
                    if path[-1][0] == here and there not in [p for p, _ in path]:
                        paths.append([*path, (there, f"{key} = {unique}")])
        for t, on in paths[0][1:] if paths else []:
            if t not in have:
                have.append(t)
                steps.append((t, on))
    return steps


def compose(query: str, tables: list[str], terms: dict[str, tuple[str, str, str]]) -> str:
    """A statement for a question over several tables: aggregate, measure, filters and grouping from its words.

    Column names are met by their words without the prefix; business terms only if
    ``terms`` explains them. Without a measure, rows are counted.
    """
    q = words_of(query)
    text = " ".join(q)
    columns = {" ".join(words_of(c.split("_", 1)[1] if "_" in c else c)): (t, c) for t in reversed(tables) for c in SEMANTIC[t]}
    found = lambda part: max((k for k in columns if re.search(rf"\b{re.escape(k)}\b", part)), key=len, default=None)
    head, _, tail = text.partition(" per ")
    group = found(tail) if tail else None
    agg = next((a for p, a in _AGGREGATES if re.search(rf"\b({p})\b", head)), "count")
    term = next((w for w in q if terms.get(w, ("",))[0] == "measure"), None)
    plain = found(head)
    measure, home = (terms[term][1], terms[term][2]) if term else (columns[plain][1], columns[plain][0]) if plain else ("*", tables[0])
    filters = [terms[w] for w in q if terms.get(w, ("",))[0] == "filter"]
    used = [home, *[t for _, _, t in filters], *([columns[group][0]] if group else [])]
    path = join_path(list(dict.fromkeys(used)))
    body = " ".join(t if not on else f"JOIN {t} ON {on}" for t, on in path)
    what = "count(*)" if agg == "count" or measure == "*" else f"round({agg}({measure}), 2)"
    where = " WHERE " + " AND ".join(f for _, f, _ in filters) if filters else ""
    return f"SELECT {columns[group][1] + ', ' if group else ''}{what} AS answer FROM {body}{where}" + (f" GROUP BY {columns[group][1]}" if group else "")


def words_of(text: str) -> list[str]:
    return re.findall(r"[a-z0-9]+", text.lower())


# --- generate, run, repair ---------------------------------------------------

_AGGREGATES = [("average|mean", "avg"), ("total|sum", "sum"), ("how many|number of|count", "count"), ("largest|highest|maximum", "max"), ("smallest|lowest|minimum", "min")]


def generate(query: str, tables: list[str], feedback: str = "", names: dict[str, str] | None = None) -> str:
    """A statement from the frame of the question: aggregate, measure, grouping. ``feedback`` of a failed try turns vague names into real columns."""
    q = query.lower()
    agg = next((a for p, a in _AGGREGATES if re.search(p, q)), "count")
    columns = [(t, c) for t in tables for c in SEMANTIC[t]]
    said = [(t, c) for t, c in columns if c in q or re.sub("^[a-z]+_", "", c) in q.split()]
    table, column = said[0] if said else (tables[0], KEY_OF[tables[0]])
    by = re.search(r" (?:by|per) (\w+)", q)
    shown = column if feedback else re.sub("^[a-z]+_", "", column)  # the first try trusts the question's wording
    group = next((c for t, c in columns if by and t == table and (c == by[1] or re.sub("^[a-z]+_", "", c) == by[1])), None)
    what = "count(*)" if agg == "count" else f"{agg}({shown})"
    return f"SELECT {group}, {what} AS answer FROM {table} GROUP BY {group}" if group else f"SELECT {what} AS answer FROM {table}"


def loop(spark: SparkSession, question: tuple[str, str], tables: dict[str, DataFrame], max_rounds: int = 3) -> DataFrame:
    """(query_id, round, sql, status, error_class): generate, run, feed the error back, at most ``max_rounds`` times."""
    out, feedback = [], ""
    for turn in range(1, max_rounds + 1):
        sql = generate(question[1], list(tables), feedback)
        got = run_sql(spark, [(question[0], sql)], tables).first()
        out.append((question[0], turn, sql, got.status, got.error_class))
        feedback = got.error_class
        if got.status == "ok":
            break
    return spark.createDataFrame(out, "query_id string, round int, sql string, status string, error_class string")


def report(runs: DataFrame) -> DataFrame:
    """Runs, share of success and mean rounds, by class and overall."""
    return runs.cube("class").agg(F.count("*").alias("runs"), F.round(F.avg((F.col("status") == "ok").cast("int")), 6).alias("success"), F.round(F.avg("rounds"), 6).alias("rounds"))


def chart_facts(series: DataFrame) -> DataFrame:
    """(name, slope, top_x, top_y, n_outliers) of each series (name, x, y)."""
    m = series.groupBy("name").agg(F.avg("y").alias("m"), F.stddev_samp("y").alias("s"))
    both = series.join(F.broadcast(m), "name")
    far = F.abs(F.col("y") - F.col("m")) > 2 * F.col("s")
    return both.groupBy("name").agg(F.round(F.regr_slope("y", "x"), 6).alias("slope"), F.max_by("x", F.struct("y", "x")).alias("top_x"), F.max("y").alias("top_y"), F.count_if(far).alias("n_outliers"))


def expire(activity: DataFrame, idle: str = "6 hours") -> DataFrame:
    """(session, started, last_activity, expires_at): sandboxes end when idle for the limit. Gaps and islands on the time line of each session."""
    w = Window.partitionBy("session").orderBy("ts")
    gap = F.expr(f"ts >= lag(ts) over (partition by session order by ts) + interval {idle}")
    marked = activity.withColumn("new", F.coalesce(gap, F.lit(True)).cast("int")).withColumn("run", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return marked.groupBy("session", "run").agg(F.min("ts").alias("started"), F.max("ts").alias("last_activity")).select("session", "started", "last_activity", F.expr(f"last_activity + interval {idle}").alias("expires_at"))


# --- DSL and DAG -------------------------------------------------------------


class Dsl:
    """Pipes of few verbs, compiled to DataFrame calls: ``from t | keep cond | with n = expr | group a, b : f = agg & g = agg | top 5 by c | show a, b``."""

    VERBS = ("from", "keep", "with", "group", "top", "show")

    @staticmethod
    def parse(text: str) -> list[tuple[str, str]]:
        steps = []
        for part in text.split("|"):
            verb, _, rest = part.strip().partition(" ")
            if verb not in Dsl.VERBS:
                raise ValueError(f"unknown verb {verb!r}")
            if re.search(r";|\b(select|insert|drop|create|delete)\b", rest, re.I):
                raise ValueError(f"not allowed in {verb!r}")
            steps.append((verb, rest.strip()))
        if not steps or steps[0][0] != "from":
            raise ValueError("a pipe begins with 'from'")
        return steps

    @staticmethod
    def compile(text: str, tables: Callable[[str], DataFrame]) -> DataFrame:
        df = None
        for verb, rest in Dsl.parse(text):
            if verb == "from":
                df = tables(rest)
            elif verb == "keep":
                df = df.where(rest)
            elif verb == "with":
                name, _, e = rest.partition("=")
                df = df.withColumn(name.strip(), F.expr(e))
            elif verb == "group":
                keys, _, aggs = rest.partition(":")
                made = [F.expr(e.partition("=")[2]).alias(e.partition("=")[0].strip()) for e in aggs.split("&")]
                df = df.groupBy(*[k.strip() for k in keys.split(",") if k.strip()]).agg(*made)
            elif verb == "top":
                n, _, by = rest.partition(" by ")
                df = df.orderBy(F.desc(by.strip()), *[c for c in df.columns if c != by.strip()]).limit(int(n))
            else:
                df = df.select(*[c.strip() for c in rest.split(",")])
        return df


class Dag:
    """Named steps (DataFrames of their parents in, DataFrame out), run in topological order."""

    def __init__(self, nodes: dict[str, Callable[..., DataFrame]], edges: list[tuple[str, str]]):
        self.nodes, self.parents = nodes, {n: [a for a, b in edges if b == n] for n in nodes}

    def order(self) -> list[str]:
        done: list[str] = []
        while len(done) < len(self.nodes):
            ready = [n for n in self.nodes if n not in done and all(p in done for p in self.parents[n])]
            if not ready:
                raise ValueError("the steps wait for each other")
            done += ready
        return done

    def run(self) -> dict[str, DataFrame]:
        out: dict[str, DataFrame] = {}
        for n in self.order():
            out[n] = self.nodes[n](*[out[p] for p in self.parents[n]])
        return out


__all__ = ["error_class"]
