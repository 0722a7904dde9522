"""Generated code and questions over the given tables, with planted faults."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tablemill.functions import det


def code_samples(orders: DataFrame) -> DataFrame:
    """One short program for each customer and half: SQL and Python with a comment; one in five has a missing parenthesis."""
    base = orders.groupBy(F.col("o_custkey").alias("code_id")).agg(F.count("*").alias("n"))
    broken = det.pick(5, "broken", F.col("code_id")) == 0
    sql = det.pick(2, "lang", F.col("code_id")) == 0
    key = F.col("code_id").cast("string")
    close = F.when(broken, "").otherwise(")")
    python = F.concat(F.lit("# totals of customer "), key, F.lit("\nrows = [r for r in orders if r.key == "), key, F.lit("]\nprint(sum(r.total for r in rows"), close, F.lit(")\n"))
    query = F.concat(F.lit("-- totals of customer "), key, F.lit("\nSELECT count(*), sum(o_totalprice"), close, F.lit(" FROM orders WHERE o_custkey = "), key)
    return base.select("code_id", F.when(sql, "sql").otherwise("python").alias("lang"), F.when(sql, query).otherwise(python).alias("text"), (~broken).alias("ok"))


CODE_SQL = f"""
WITH b AS (SELECT o_custkey AS code_id, {det.sql_pick(5, "'broken'", 'o_custkey')} = 0 AS broken, {det.sql_pick(2, "'lang'", 'o_custkey')} = 0 AS is_sql FROM orders GROUP BY o_custkey),
code AS (SELECT code_id, CASE WHEN is_sql THEN 'sql' ELSE 'python' END AS lang, CASE WHEN is_sql
  THEN '-- totals of customer ' || code_id || chr(10) || 'SELECT count(*), sum(o_totalprice' || CASE WHEN broken THEN '' ELSE ')' END || ' FROM orders WHERE o_custkey = ' || code_id
  ELSE '# totals of customer ' || code_id || chr(10) || 'rows = [r for r in orders if r.key == ' || code_id || ']' || chr(10) || 'print(sum(r.total for r in rows' || CASE WHEN broken THEN '' ELSE ')' END || ')' || chr(10) END AS text, NOT broken AS ok FROM b)
"""


def compile_ok(code: DataFrame, text: str = "text") -> DataFrame:
    """``compiles``: whether Python text parses; nothing is run."""

    @F.pandas_udf("boolean")
    def parses(texts: pd.Series) -> pd.Series:
        import ast

        def one(x):
            try:
                ast.parse(x or "")
                return True
            except (SyntaxError, ValueError, MemoryError, RecursionError):
                return False

        return texts.map(one)

    return code.withColumn("compiles", parses(F.col(text)))
