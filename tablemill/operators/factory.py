"""Samples of table, question and answer: generated questions, turns, executors, cleaning stages and augmentation.

Where the method calls a language model, a template grammar stands in behind
the same DataFrame contract.
"""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tablemill.functions import det

# Semantic type of each column of the star tables.
SEMANTIC = {
    "customer": {"c_custkey": "key", "c_name": "name", "c_nationkey": "key", "c_acctbal": "money", "c_mktsegment": "category"},
    "supplier": {"s_suppkey": "key", "s_name": "name", "s_nationkey": "key", "s_acctbal": "money"},
    "part": {"p_partkey": "key", "p_name": "text", "p_brand": "category", "p_type": "category", "p_size": "quantity", "p_retailprice": "money"},
    "orders": {"o_orderkey": "key", "o_custkey": "key", "o_orderstatus": "category", "o_totalprice": "money", "o_orderdate": "date", "o_orderpriority": "category"},
    "lineitem": {"l_orderkey": "key", "l_partkey": "key", "l_suppkey": "key", "l_linenumber": "quantity", "l_quantity": "quantity", "l_extendedprice": "money", "l_discount": "rate", "l_tax": "rate", "l_returnflag": "category", "l_linestatus": "category", "l_shipdate": "date"},
    "nation": {"n_nationkey": "key", "n_name": "name", "n_regionkey": "key"},
    "events": {"event_id": "key", "ts": "date", "user_id": "key", "event_type": "category", "value": "money"},
}
KEY_OF = {"customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey", "nation": "n_nationkey", "events": "event_id"}
NUMERIC = ("money", "quantity", "rate")

# (class, kind of column, question, SQL); {t} table, {c} column, {k} key.
TEMPLATES = [
    ("retrieval", "number", "Which {t} rows have the five largest {c}?", "SELECT {k}, {c} FROM {t} ORDER BY {c} DESC, {k} LIMIT 5"),
    ("retrieval", "category", "List each {c} that occurs in {t}.", "SELECT DISTINCT {c} FROM {t}"),
    ("insertion", "number", "Add a row to {t} with {c} set to zero.", "INSERT INTO {t} ({c}) VALUES (0)"),
    ("insertion", "category", "Insert a new record into {t} whose {c} is empty.", "INSERT INTO {t} ({c}) VALUES ('')"),
    ("deletion", "number", "Remove the {t} rows whose {c} is negative.", "DELETE FROM {t} WHERE {c} < 0"),
    ("deletion", "category", "Delete {t} records without a {c}.", "DELETE FROM {t} WHERE {c} IS NULL"),
    ("modification", "number", "Raise {c} of every {t} row by five percent.", "UPDATE {t} SET {c} = {c} * 1.05"),
    ("modification", "category", "Change {c} in {t} to upper case.", "UPDATE {t} SET {c} = upper({c})"),
    ("computation", "number", "What is the total {c} over all {t} rows?", "SELECT sum({c}) AS total FROM {t}"),
    ("computation", "number", "How far apart are the largest and the smallest {c} in {t}?", "SELECT max({c}) - min({c}) AS spread FROM {t}"),
    ("statistics", "number", "What are the mean and the standard deviation of {c} in {t}?", "SELECT avg({c}) AS mean, stddev_samp({c}) AS sd FROM {t}"),
    ("statistics", "category", "How often does each {c} occur in {t} on average and at most?", "SELECT avg(n) AS mean, max(n) AS top FROM (SELECT {c}, count(*) AS n FROM {t} GROUP BY {c})"),
    ("visualisation", "number", "Plot the distribution of {c} in {t}.", "SELECT floor({c} / 100) AS bin, count(*) AS n FROM {t} GROUP BY 1"),
    ("visualisation", "category", "Draw a bar chart of {t} rows by {c}.", "SELECT {c}, count(*) AS n FROM {t} GROUP BY {c}"),
    ("fuzzy", "table", "Which {t} rows perform best?", None),
    ("fuzzy", "table", "What stands out in {t}?", None),
]

# First match wins.
CLASS_RULES = [("fuzzy", "perform best|stands out"), ("insertion", "^add |^insert "), ("deletion", "^remove |^delete "), ("modification", "^raise |^change "), ("visualisation", "^plot |chart"), ("statistics", "mean|average|deviation"), ("computation", "total|how far"), ("retrieval", ".")]

JARGON = {"revenue": "extended price after discount", "churned": "without an order", "top seller": "largest quantity", "late": "shipped after the order year"}


def columns_frame(spark: SparkSession) -> DataFrame:
    rows = [(t, c, s, "number" if s in NUMERIC else "category" if s == "category" else "other", KEY_OF[t]) for t, cs in SEMANTIC.items() for c, s in cs.items()]
    rows += [(t, "", "table", "table", KEY_OF[t]) for t in SEMANTIC]
    return spark.createDataFrame(rows, "table_id string, col string, sem string, kind string, key string")


def templates_frame(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(i, *t) for i, t in enumerate(TEMPLATES)], "template int, class string, kind string, question string, sql string")


def questions(spark: SparkSession) -> DataFrame:
    """(sample_id, table_id, class, query, gold_sql): every template over every column it fits."""
    both = columns_frame(spark).join(F.broadcast(templates_frame(spark)), "kind")
    fill = lambda c: F.replace(F.replace(F.replace(c, F.lit("{t}"), F.col("table_id")), F.lit("{c}"), F.col("col")), F.lit("{k}"), F.col("key"))
    return both.select(F.concat_ws("-", F.col("template").cast("string"), "table_id", "col").alias("sample_id"), "table_id", "col", "class", fill(F.col("question")).alias("query"), fill(F.col("sql")).alias("gold_sql"))


def classify(query: Column) -> Column:
    out = None
    for name, pattern in CLASS_RULES:
        hit = F.lower(query).rlike(pattern)
        out = F.when(hit, name) if out is None else out.when(hit, name)
    return out


def clarify(qs: DataFrame, cols: DataFrame) -> DataFrame:
    """Fuzzy questions with a follow-up that lists the measures they could mean."""
    m = cols.where("kind = 'number'").groupBy("table_id").agg(F.array_join(F.array_sort(F.collect_list("col")), ", ").alias("measures"))
    return qs.where("class = 'fuzzy'").join(m, "table_id", "left").select("sample_id", F.concat(F.lit("Which measure do you mean: "), F.coalesce("measures", F.lit("number of rows")), F.lit("?")).alias("follow_up"))


def with_jargon(query: Column, words: dict[str, str]) -> Column:
    for k, v in words.items():
        query = F.replace(query, F.lit(k), F.lit(v))
    return query


def drafts(qs: DataFrame) -> DataFrame:
    """A weak first answer to each question with SQL: right, a wrong column, a syntax fault, comments only, or another language."""
    d = det.pick(5, "draft", F.col("sample_id"))
    sql = F.col("gold_sql")
    draft = F.when(d == 0, F.replace(sql, F.col("col"), F.concat("col", F.lit("_x")))).when(d == 1, F.replace(sql, F.lit("FROM"), F.lit("FORM"))).when(d == 2, F.concat(F.lit("-- "), sql)).when(d == 3, F.lit("import pandas as pd\nprint(1)")).otherwise(sql)
    return qs.where("gold_sql is not null").withColumn("fault", F.get(F.array(*map(F.lit, ["column", "syntax", "comment", "language", "none"])), d)).withColumn("draft", draft)


def repair_pairs(d: DataFrame) -> DataFrame:
    """Two turns for each faulty draft: the draft, then the better answer."""
    return d.where("fault <> 'none'").select("sample_id", F.inline(F.array(F.struct(F.lit(0).alias("turn"), F.col("draft").alias("code")), F.struct(F.lit(1).alias("turn"), F.col("gold_sql").alias("code")))))


def chains(orders: DataFrame, lines: DataFrame) -> DataFrame:
    """Three questions on the orders of one day, each depending on the one before, with their answers."""
    per = orders.groupBy(F.date_format("o_orderdate", "yyyy-MM-dd").alias("chain_id")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))
    tax = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.date_format("o_orderdate", "yyyy-MM-dd").alias("chain_id")).agg(F.round(F.avg("l_tax"), 6).alias("tax"))
    turn = lambda i, q, a: F.struct(F.lit(i).alias("turn"), F.lit(q).alias("query"), a.cast("double").alias("answer"))
    asked = F.array(turn(0, "How many orders were placed that day?", F.col("n")), turn(1, "What is their total?", F.col("total")), turn(2, "What is the mean tax rate of their lines?", F.col("tax")))
    out = per.join(tax, "chain_id", "left").select("chain_id", F.inline(asked))
    return out.withColumn("failed", F.col("answer").isNull() | (det.unit("fail", F.col("chain_id"), F.col("turn")) < 0.1))


def truncate(turns: DataFrame) -> DataFrame:
    """Cut each chain before its first failed turn; nothing stays of a chain that fails at once."""
    first = turns.groupBy("chain_id").agg(F.min(F.when(F.col("failed"), F.col("turn"))).alias("cut"))
    return turns.join(first, "chain_id").where(F.col("cut").isNull() | (F.col("turn") < F.col("cut"))).drop("cut")


PROMPTS = [
    "Table: {t}\nQuestion: {q}\nAnswer with SQL.", "You know the table {t}. {q} Write one query.", "{q} (table {t})", "Given {t}, answer: {q}", "Task: {q}\nSource: {t}",
    "As an analyst of {t}: {q}", "SQL for {t}. {q}", "Data: {t}. Request: {q}", "{t} | {q}", "Please answer from {t}: {q}", "Use only {t}. {q} Show the code.",
]


def prompts(qs: DataFrame, templates: list[str] | None = None) -> DataFrame:
    templates = templates or PROMPTS
    chosen = F.get(F.array(*map(F.lit, templates)), det.pick(len(templates), "prompt", F.col("sample_id")))
    return qs.select("sample_id", F.replace(F.replace(chosen, F.lit("{t}"), F.col("table_id")), F.lit("{q}"), F.col("query")).alias("prompt"))


def shape(d: DataFrame, style: str) -> DataFrame:
    """An answer as thought and code, as observe-and-act turns, or as plan, code and text."""
    code = F.col("gold_sql")
    if style == "thought":
        text = F.concat(F.lit("Thought: the question is a "), "class", F.lit(" on "), "table_id", F.lit(".\nCode: "), code)
    elif style == "observe":
        text = F.concat(F.lit("Act: "), F.col("draft"), F.lit("\nObserve: "), "fault", F.lit("\nAct: "), code)
    elif style == "plan":
        text = F.concat(F.lit("Plan: 1. read "), "table_id", F.lit(" 2. compute 3. report\n"), code, F.lit("\nThe result answers: "), "query")
    else:
        raise ValueError(style)
    return d.select("sample_id", F.lit(style).alias("style"), text.alias("answer"))


# --- executors ---------------------------------------------------------------

ALLOWED = re.compile(r"^\s*(select|with|values)\b", re.I)
BLOCKED = re.compile(r"\b(insert|update|delete|drop|create|alter|truncate|merge|grant|set|cache|refresh|add|load|export|call)\b", re.I)


def admissible(sql: str) -> bool:
    """One SELECT, WITH or VALUES statement without a word that writes."""
    bare = re.sub(r"--[^\n]*|/\*.*?\*/|'(?:[^']|'')*'", " ", sql, flags=re.S).strip().rstrip(";")
    return bool(ALLOWED.match(bare)) and ";" not in bare and not BLOCKED.search(bare)


def error_class(condition: Column) -> Column:
    return (
        F.when(condition == "", "ok").when(condition.rlike("UNRESOLVED|TABLE_OR_VIEW|FIELD_NOT_FOUND"), "field_mismatch").when(condition.rlike("CAST|DATATYPE_MISMATCH|NUMERIC|CONVERSION"), "type_error")
        .when(condition.rlike("PARSE|SYNTAX"), "syntax").when(condition.rlike("CANCEL|TIMEOUT"), "timeout").when(condition == "EMPTY", "empty").when(condition == "REFUSED", "refused").otherwise("other")
    )


def run_sql(spark: SparkSession, samples: list[tuple[str, str]], tables: dict[str, DataFrame], timeout: float = 60.0, threads: int = 8) -> DataFrame:
    """(sample_id, status, condition, n_rows, rows_hash) of admitted statements, each with a tag that a timer interrupts.

    A bounded list of statements runs from the driver, ``threads`` at a time; their
    data work is distributed. The count and the hash, which is free of order, are
    taken over the whole result; only these come back.
    """
    from concurrent.futures import ThreadPoolExecutor

    own = spark.newSession()
    for name, df in tables.items():
        # Views of the new session read the same files.
        own.read.parquet(*df.inputFiles()).createOrReplaceTempView(name)
    with ThreadPoolExecutor(threads) as pool:
        out = list(pool.map(lambda s: (s[0], *_run_one(own, s[1], timeout)), samples))
    made = spark.createDataFrame(out, "sample_id string, status string, condition string, n_rows long, rows_hash string")
    return made.withColumn("error_class", error_class(F.col("condition")))


def _run_one(own: SparkSession, sql: str, timeout: float) -> tuple[str, str, int, str]:
    import hashlib
    import threading
    import uuid

    from pyspark.errors import PySparkException

    condition, n, digest = "", 0, ""
    if not admissible(sql):
        return "error", "REFUSED", 0, ""
    context, tag = own.sparkContext, f"tm-{uuid.uuid4().hex}"
    context.addJobTag(tag)
    timer = threading.Timer(timeout, context.cancelJobsWithTag, [tag])
    timer.start()
    try:
        found = own.sql(sql)
        kinds = [kind for _, kind in found.dtypes]
        found = found.toDF(*[f"c{i}" for i in range(len(kinds))])
        shown = [F.coalesce(F.when(F.col(f"c{i}").isNotNull(), F.format_string("%.4f", f"c{i}")) if kind in ("double", "float") else F.col(f"c{i}").cast("string"), F.lit("None")) for i, kind in enumerate(kinds)]
        sums = [F.sum(F.xxhash64(F.lit(seed), *shown).cast("decimal(38,0)")) for seed in (0, 1)]
        n, *sums = found.agg(F.count("*"), *sums).first()
        condition = "" if n else "EMPTY"
        digest = hashlib.md5(f"{n}|{sums}".encode()).hexdigest()
    except PySparkException as e:
        condition = e.getCondition() or "OTHER"
    except Exception:
        condition = "CANCELLED"
    finally:
        timer.cancel()
        context.removeJobTag(tag)
    return "error" if condition else "ok", condition, n, digest


_RUNNER = """
import resource, sys
resource.setrlimit(resource.RLIMIT_AS, (int(sys.argv[1]) << 20, int(sys.argv[1]) << 20))
resource.setrlimit(resource.RLIMIT_CPU, (int(sys.argv[2]), int(sys.argv[2])))
resource.setrlimit(resource.RLIMIT_FSIZE, (0, 0))
resource.setrlimit(resource.RLIMIT_NOFILE, (16, 16))
code = sys.stdin.read()

def guard(event, args):
    writes = event == "open" and ((isinstance(args[1], str) and set(args[1]) & set("wax+")) or (args[2] or 0) & 0o1103)
    if writes or event.startswith(("socket.", "subprocess.", "shutil.", "os.system", "os.exec", "os.fork", "os.spawn", "os.posix_spawn", "os.remove", "os.rename", "os.mkdir", "os.rmdir", "ctypes.")):
        raise PermissionError(event)

sys.addaudithook(guard)
try:
    exec(compile(code, "sample", "exec"), {"__name__": "sample"})
except BaseException as e:
    sys.stdout.flush()
    print("\\0" + type(e).__name__, end="", flush=True)
"""

_KINDS = {"KeyError": "field_mismatch", "NameError": "field_mismatch", "TypeError": "type_error", "ValueError": "type_error", "SyntaxError": "syntax", "IndentationError": "syntax"}


def run_python(samples: DataFrame, seconds: int = 5, memory_mb: int = 512, output_mb: int = 64) -> DataFrame:
    """(sample_id, status, error_class, output): each program in a child process with limits on time, memory, files and output.

    The output is whole; a program that writes more than ``output_mb`` is ended with
    the class ``output``, as one that takes too long is with ``timeout``.
    """

    def one(code: str) -> tuple[str, str]:
        import subprocess
        import sys
        import threading

        child = subprocess.Popen([sys.executable, "-I", "-c", _RUNNER, str(memory_mb), str(seconds)], stdin=subprocess.PIPE, stdout=subprocess.PIPE, stderr=subprocess.DEVNULL, env={"PATH": ""}, cwd="/")
        late = threading.Timer(seconds + 2, child.kill)
        late.start()
        try:
            child.stdin.write(code.encode())
            child.stdin.close()
            data = child.stdout.read((output_mb << 20) + 1)
            if len(data) > output_mb << 20:
                child.kill()
                return "output", ""
            ended = child.wait()
        except BrokenPipeError:
            ended, data = child.wait(), b""
        finally:
            late.cancel()
            child.stdout.close()
        if ended in (-9, -24):
            return "timeout", ""
        text, mark, error = data.decode("utf-8", "replace").partition("\0")
        return (_KINDS.get(error, "other") if mark else "ok" if ended == 0 else "other"), text

    def run(frames):
        for pdf in frames:
            for sample, code in zip(pdf.sample_id, pdf.code):
                kind, text = one(code or "")
                yield pd.DataFrame([(sample, "ok" if kind == "ok" else "error", kind, text)], columns=["sample_id", "status", "error_class", "output"])

    return samples.select("sample_id", "code").mapInPandas(run, "sample_id string, status string, error_class string, output string")


# --- cleaning of samples -----------------------------------------------------


def redefines_table(code: Column) -> Column:
    return code.rlike(r"(?i)create\s+(temp\w*\s+)?(table|view)|pd\.DataFrame\s*\(\s*[\[{]|with\s+\w+\s+as\s*\(\s*values")


def language_of(code: Column) -> Column:
    return F.when(code.rlike(r"(?m)^\s*(import |from \w+ import|print\(|def )|\bpd\."), "python").when(code.rlike(r"(?i)\b(select|insert|update|delete)\b"), "sql").otherwise("none")


def comment_only(code: Column) -> Column:
    return F.trim(F.regexp_replace(F.regexp_replace(code, r"(?m)^\s*(--|#)[^\n]*$", ""), r"\s+", "")) == ""


SCORERS = ["field_coverage", "code_detail", "clarity"]


def score(d: DataFrame) -> DataFrame:
    """(sample_id, scorer, value): stand-in scorers in 0..1 on the code and its question."""
    code = F.col("draft")
    coverage = F.when(F.contains(F.lower(code), F.lower("table_id")), 0.5).otherwise(0.0) + F.when(F.col("col") == "", 0.5).when(F.regexp_instr(code, F.concat(F.lit("\\b"), F.col("col"), F.lit("\\b"))) > 0, 0.5).otherwise(0.0)
    detail = F.least(F.lit(1.0), F.size(F.split(F.trim(code), r"\s+")) / 4)
    clarity = F.when(comment_only(code), 0.0).when(F.length(code) > 400, 0.5).otherwise(1.0)
    pairs = F.array(*[F.struct(F.lit(n).alias("scorer"), v.cast("double").alias("value")) for n, v in zip(SCORERS, (coverage, detail, clarity))])
    return d.select("sample_id", F.inline(pairs))


def keep(scores: DataFrame, threshold: float = 0.75) -> DataFrame:
    """Samples that every scorer puts at the threshold or above."""
    return scores.groupBy("sample_id").agg(F.min("value").alias("least")).where(F.col("least") >= threshold).select("sample_id")


def calibrate(rows: DataFrame, n: int = 200, gate: float = 0.95, seed: str = "cal") -> DataFrame:
    """(n, right, rate, low, high, passed): a drawn sample of each batch against the gate, with a Wilson interval."""
    w = Window.partitionBy("batch").orderBy(det.text(seed, F.col("sample_id")))
    drawn = rows.withColumn("r", F.row_number().over(w)).where(F.col("r") <= n)
    g = drawn.groupBy("batch").agg(F.count("*").alias("n"), F.count_if("right").alias("right"))
    p, m, z = F.col("right") / F.col("n"), F.col("n"), 1.96
    centre, half = (p + z * z / (2 * m)) / (1 + z * z / m), z * F.sqrt(p * (1 - p) / m + z * z / (4 * m * m)) / (1 + z * z / m)
    return g.select("batch", "n", "right", F.round(p, 6).alias("rate"), F.round(centre - half, 6).alias("low"), F.round(centre + half, 6).alias("high"), (p >= gate).alias("passed"))


def staged(d: DataFrame, tables: dict[str, DataFrame], least: float = 0.75, gate: float = 0.95) -> list[tuple[str, DataFrame]]:
    """The stages of cleaning in order; each takes what the one before left.

    Rules on the code; scores of question and code alone; a run of draft and
    reference, which must both end well with equal results; scores of the full
    record; a gate for each question class, whose drawn part must be right often
    enough; and a validation part, drawn by hash, that never enters training.
    """
    spark = d.sparkSession
    rules = d.where(~redefines_table(F.col("draft")) & ~comment_only(F.col("draft")) & (language_of(F.col("draft")) == "sql"))
    first = rules.join(keep(score(rules).where("scorer <> 'clarity'"), least / 1.5), "sample_id", "left_semi")
    asked = first.where(F.col("table_id").isin(*tables)).select("sample_id", "draft", "gold_sql").orderBy("sample_id").collect()
    statements = sorted({s for r in asked for s in (r.draft, r.gold_sql)})
    ran = {r.sample_id: (r.status, r.rows_hash) for r in run_sql(spark, [(s, s) for s in statements], tables).collect()}
    right = [(r.sample_id,) for r in asked if ran[r.draft][0] == "ok" and ran[r.draft] == ran[r.gold_sql]]
    runs = first.join(spark.createDataFrame(right, "sample_id string"), "sample_id", "left_semi")
    scored = runs.join(keep(score(runs), least), "sample_id", "left_semi")
    passed = calibrate(scored.select(F.col("class").alias("batch"), "sample_id", (classify(F.col("query")) == F.col("class")).alias("right")), gate=gate).where("passed").select(F.col("batch").alias("class"))
    gated = scored.join(passed, "class", "left_semi")
    return [("generated", d), ("rules", rules), ("scored", first), ("executed", runs), ("scored_again", scored), ("gated", gated), ("training", gated.where(det.unit("split", F.col("sample_id")) < 0.9))]


def question_sets(qs: DataFrame, sets: int = 3) -> DataFrame:
    """(set_id, sample_id, prompt): several question sets for each table; a question comes in each set in a wording drawn for it."""
    each = qs.select("*", F.explode(F.sequence(F.lit(0), F.lit(sets - 1))).alias("set_id"))
    chosen = F.get(F.array(*map(F.lit, PROMPTS)), det.pick(len(PROMPTS), "set", F.col("set_id"), F.col("sample_id")))
    return each.select("set_id", "table_id", "sample_id", F.replace(F.replace(chosen, F.lit("{t}"), F.col("table_id")), F.lit("{q}"), F.col("query")).alias("prompt"))


GENERATORS = {"small": "Ask briefly: {k} on {t}.", "large": "Think of an analyst of {t} and write one {k} question with its answer."}


def registry(spark: SparkSession) -> DataFrame:
    """(generator, class, prompt): each generator's own prompt for each class of question."""
    classes = sorted({c for c, *_ in TEMPLATES})
    return spark.createDataFrame([(g, c, p.replace("{k}", c)) for g, p in GENERATORS.items() for c in classes], "generator string, class string, prompt string")


# --- augmentation ------------------------------------------------------------


def blur_names(query: Column, table: Column, column: Column) -> Column:
    """Field and table names in a question become vague mentions."""
    vague = F.when(column == "", F.lit("")).otherwise(F.concat(F.lit("the "), F.replace(F.regexp_replace(column, "^[a-z]+_", ""), F.lit("_"), F.lit(" "))))
    q = F.when(column == "", query).otherwise(F.replace(query, column, vague))
    return F.replace(q, F.concat(F.lit(" "), table), F.lit(" the data"))


def append_requests(qs: DataFrame, rate: float = 0.3) -> DataFrame:
    u = det.unit("append", F.col("sample_id"))
    extra = F.when(u < rate / 2, " Also draw a chart.").when(u < rate, " Sum up the result in one sentence.").otherwise("")
    return qs.select("sample_id", F.concat("query", extra).alias("query"))


def combine_turns(qs: DataFrame, rate: float = 0.5) -> DataFrame:
    """Questions on one table, single or joined in twos into two-turn samples."""
    w = Window.partitionBy("table_id").orderBy(det.text("turns", F.col("sample_id")))
    r = qs.withColumn("r", F.row_number().over(w) - 1).withColumn("pair", F.floor(F.col("r") / 2)).withColumn("joined", det.unit("join", F.col("table_id"), F.col("pair")) < rate)
    key = F.when(F.col("joined"), F.concat_ws("-", F.lit("pair"), "table_id", F.col("pair").cast("string"))).otherwise(F.col("sample_id"))
    return r.groupBy(key.alias("sample_id")).agg(F.count("*").alias("turns"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("r", "query"))), lambda x: x["query"]), "\n").alias("text"))


SFT_SHARES = {"agent": 0.0209, "coding": 0.2151, "table": 0.3482, "mathematics": 0.0822, "general": 0.3336}


# --- further sample kinds ----------------------------------------------------


def tool_calls(qs: DataFrame) -> DataFrame:
    """A call of the query tool as JSON for each question with SQL."""
    return qs.where("gold_sql is not null").select("sample_id", F.to_json(F.struct(F.lit("query").alias("tool"), F.struct(F.col("table_id").alias("table"), F.col("gold_sql").alias("sql")).alias("arguments"))).alias("call"))


def table_specs(parts: DataFrame) -> DataFrame:
    """Table generation: a description with constraints, and a table that meets them."""
    spec = parts.groupBy("p_type").agg(F.count("*").alias("n"), F.min("p_retailprice").alias("low"), F.max("p_retailprice").alias("high"))
    rows = F.transform(F.sequence(F.lit(1), F.lit(3)), lambda i: F.concat(F.col("p_type"), F.lit("-"), i.cast("string"), F.lit(","), F.round(F.col("low") + (F.col("high") - F.col("low")) * i / 4, 2).cast("string")))
    return spec.select(F.col("p_type").alias("sample_id"), F.concat(F.lit("Make a table of three "), F.lower("p_type"), F.lit(" items with prices between "), F.col("low").cast("string"), F.lit(" and "), F.col("high").cast("string")).alias("instruction"), F.concat(F.lit("item,price\n"), F.array_join(rows, "\n")).alias("output"))


def receipts(orders: DataFrame, lines: DataFrame) -> DataFrame:
    """One text receipt an order."""
    item = F.concat(F.lit("part "), F.col("l_partkey").cast("string"), F.lit(" x "), F.col("l_quantity").cast("string"))
    body = lines.groupBy("l_orderkey").agg(F.array_join(F.array_sort(F.collect_list(item)), "\n").alias("body"))
    return orders.join(body, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_orderkey").alias("doc_id"), F.concat(F.lit("RECEIPT "), F.col("o_orderkey").cast("string"), F.lit("\n"), "body", F.lit("\nTOTAL "), F.col("o_totalprice").cast("string")).alias("text"))


def parse_receipts(docs: DataFrame) -> DataFrame:
    """Receipt text back to rows."""
    hits = F.regexp_extract_all("text", F.lit(r"part [0-9]+ x [0-9.]+"), F.lit(0))
    each = docs.select("doc_id", F.explode(hits).alias("h"))
    return each.select("doc_id", F.regexp_extract("h", "part ([0-9]+)", 1).cast("long").alias("part"), F.regexp_extract("h", "x ([0-9.]+)", 1).cast("double").alias("quantity"))


def math_samples(parts: DataFrame) -> DataFrame:
    """Arithmetic word problems with their steps."""
    n, p = F.col("p_size"), F.col("p_retailprice")
    total = F.round(n * p, 2)
    return parts.select(F.col("p_partkey").alias("sample_id"), F.concat(F.lit("What do "), n.cast("string"), F.lit(" pieces at "), p.cast("string"), F.lit(" cost?")).alias("question"), F.concat(n.cast("string"), F.lit(" * "), p.cast("string"), F.lit(" = "), F.format_string("%.2f", total)).alias("steps"), total.alias("answer"))
