"""Semantic table encoder: hashed cell vectors, attention over both axes, fixed-size column vectors, contrastive loss.

The sentence model of the method is stood in by signed hashing of character
3-grams; everything after it works on any cell vectors of the same shape.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.functions.text import let
from tablemill.operators.tables import missing

D = 64


# --- cell vectors ------------------------------------------------------------


def gram_hits(value: Column, d: int = D) -> Column:
    """Bucket and sign of each padded 3-gram of a value, from its md5."""
    padded = F.concat(F.lit("^"), value, F.lit("$"))
    grams = let(padded, lambda p: F.transform(F.sequence(F.lit(1), F.greatest(F.length(p) - 2, F.lit(1))), lambda i: F.md5(F.substr(p, i, F.lit(3)))))
    return F.transform(grams, lambda h: F.struct((F.conv(F.substr(h, F.lit(1), F.lit(8)), 16, 10).cast("long") % d).cast("int").alias("b"), F.when(F.conv(F.substr(h, F.lit(9), F.lit(1)), 16, 10).cast("int") % 2 == 0, 1.0).otherwise(-1.0).alias("s")))


def hashed(value: Column, d: int = D) -> Column:
    """Unit vector of a value; a missing value is the zero vector."""
    zero = F.array_repeat(F.lit(0.0), d)
    raw = let(gram_hits(F.coalesce(value, F.lit("")), d), lambda hits: F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: F.aggregate(F.filter(hits, lambda h: h["b"] == j), F.lit(0.0), lambda a, h: a + h["s"])))
    unit = let(raw, lambda v: let(F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, x: a + x * x)), lambda n: F.when(n > 0, F.transform(v, lambda x: x / n)).otherwise(zero)))
    return F.when(missing(value), zero).otherwise(unit)


def embed(cells: DataFrame, d: int = D) -> DataFrame:
    """Cells with ``vec``; each distinct value is embedded once.

    The vectors are some 20 times larger than the values whose size Spark knows, so
    they are never sent to the driver for a broadcast.
    """
    values = cells.select("value").where("value is not null").distinct().withColumn("vec", hashed(F.col("value"), d))
    return cells.join(values.hint("merge"), "value", "left").withColumn("vec", F.coalesce("vec", F.array_repeat(F.lit(0.0), d)))


# --- attention over rows and columns -----------------------------------------


def weights(d: int, layers: int, seed: int = 7) -> list[dict[str, np.ndarray]]:
    rng = np.random.default_rng(seed)
    out = []
    for _ in range(2 * layers):
        w = {k: rng.normal(0, d**-0.5, (d, d)) for k in "qkvo"}
        w["up"], w["down"] = rng.normal(0, d**-0.5, (d, 4 * d)), rng.normal(0, (4 * d) ** -0.5, (4 * d, d))
        out.append(w)
    return out


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def layer_norm(x: np.ndarray) -> np.ndarray:
    return (x - x.mean(-1, keepdims=True)) / np.sqrt(x.var(-1, keepdims=True) + 1e-6)


def attend(x: np.ndarray, w: dict[str, np.ndarray], heads: int = 4) -> np.ndarray:
    """Transformer layer over axis -2, both directions visible, no position term."""
    *lead, n, d = x.shape
    split = lambda y: y.reshape(*lead, n, heads, d // heads).swapaxes(-2, -3)
    q, k, v = (split(x @ w[c]) for c in "qkv")
    mixed = (softmax(q @ k.swapaxes(-1, -2) / np.sqrt(d // heads)) @ v).swapaxes(-2, -3).reshape(*lead, n, d)
    x = layer_norm(x + mixed @ w["o"])
    return layer_norm(x + np.maximum(x @ w["up"], 0) @ w["down"])


def encode_grid(e: np.ndarray, layers: int = 2, seed: int = 7, axes: str = "both", positions: bool = False) -> np.ndarray:
    """m×n×d cells in, m×n×d out: along rows, then along columns, ``layers`` times.

    ``axes`` of 'rows' or 'columns' and ``positions`` are ablations; with
    positions, order matters again.
    """
    if positions:
        m, n, d = e.shape
        e = e + np.sin(np.arange(m)[:, None, None] / 3 + np.arange(d)) + np.cos(np.arange(n)[None, :, None] / 3 + np.arange(d))
    ws = weights(e.shape[-1], layers, seed)
    for i in range(layers):
        if axes in ("both", "rows"):
            e = attend(e, ws[2 * i])
        if axes in ("both", "columns"):
            e = attend(e.swapaxes(0, 1), ws[2 * i + 1]).swapaxes(0, 1)
    return e


def grid_of(pdf: pd.DataFrame) -> tuple[np.ndarray, list, list]:
    rows, cols = sorted(pdf.row_id.unique()), sorted(pdf.col_id.unique())
    at_r, at_c = {r: i for i, r in enumerate(rows)}, {c: i for i, c in enumerate(cols)}
    e = np.zeros((len(rows), len(cols), len(pdf.vec.iloc[0])))
    for r, c, v in zip(pdf.row_id, pdf.col_id, pdf.vec):
        e[at_r[r], at_c[c]] = v
    return e, rows, cols


def encode(cells: DataFrame, layers: int = 2, seed: int = 7, axes: str = "both", positions: bool = False) -> DataFrame:
    """Encoded cells of sampled snapshots (table_id, snap, row_id, col_id, vec); a group is one snapshot, bounded by its sample."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        e, rows, cols = grid_of(pdf)
        out = encode_grid(e, layers, seed, axes, positions)
        return pd.DataFrame([(pdf.table_id.iloc[0], pdf.snap.iloc[0], r, c, out[i, j].tolist()) for i, r in enumerate(rows) for j, c in enumerate(cols)], columns=["table_id", "snap", "row_id", "col_id", "vec"])

    return cells.groupBy("table_id", "snap").applyInPandas(run, "table_id string, snap int, row_id long, col_id int, vec array<double>")


# --- adapter -----------------------------------------------------------------


def adapter_weights(d: int, k: int = 4, d_out: int = D, seed: int = 11) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(seed)
    return {"queries": rng.normal(0, 1, (k, d)), "k": rng.normal(0, d**-0.5, (d, d)), "v": rng.normal(0, d**-0.5, (d, d)), "out": rng.normal(0, d**-0.5, (d, d_out))}


def adapter_state(x: np.ndarray, w: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Softmax state of a part of a column's cells: per query the largest score, the sum of weights, the weighted values."""
    s = w["queries"] @ (x @ w["k"]).T / np.sqrt(x.shape[1])
    top = s.max(1)
    p = np.exp(s - top[:, None])
    return top, p.sum(1), p @ (x @ w["v"])


def merge_states(a, b):
    """State of two parts together; the order of merging does not matter."""
    top = np.maximum(a[0], b[0])
    fa, fb = np.exp(a[0] - top), np.exp(b[0] - top)
    return top, a[1] * fa + b[1] * fb, a[2] * fa[:, None] + b[2] * fb[:, None]


def adapter_columns(cells: DataFrame, k: int = 4, d_out: int = D, seed: int = 11) -> DataFrame:
    """(table_id, col_id, vecs k×d_out): partial states inside each partition, merged per column; size does not grow with rows."""

    def partial(batches):
        states: dict = {}
        w = None
        for pdf in batches:
            for key, part in pdf.groupby(["table_id", "col_id"], sort=False):
                x = np.stack(part.vec.to_numpy())
                w = w or adapter_weights(x.shape[1], k, d_out, seed)
                s = adapter_state(x, w)
                states[key] = merge_states(states[key], s) if key in states else s
        yield pd.DataFrame([(t, int(c), s[0].tolist(), s[1].tolist(), s[2].ravel().tolist()) for (t, c), s in states.items()], columns=["table_id", "col_id", "top", "total", "acc"])

    def final(pdf: pd.DataFrame) -> pd.DataFrame:
        s = None
        for r in pdf.sort_values("top", key=lambda c: c.map(str)).itertuples():
            one = (np.array(r.top), np.array(r.total), np.array(r.acc).reshape(k, -1))
            s = one if s is None else merge_states(s, one)
        w = adapter_weights(s[2].shape[1], k, d_out, seed)
        return pd.DataFrame([(pdf.table_id.iloc[0], pdf.col_id.iloc[0], ((s[2] / s[1][:, None]) @ w["out"]).tolist())], columns=["table_id", "col_id", "vecs"])

    state = cells.select("table_id", "col_id", "vec").mapInPandas(partial, "table_id string, col_id int, top array<double>, total array<double>, acc array<double>")
    return state.groupBy("table_id", "col_id").applyInPandas(final, "table_id string, col_id int, vecs array<array<double>>")


def pool(cells: DataFrame, how: str = "mean") -> DataFrame:
    """Baseline: mean or maximum of each dimension over a column's cells."""
    fn = {"mean": F.avg, "max": F.max}[how]
    per = cells.select("table_id", "col_id", F.posexplode("vec").alias("dim", "x")).groupBy("table_id", "col_id", "dim").agg(fn("x").alias("x"))
    return per.groupBy("table_id", "col_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "x"))), lambda s: s["x"]).alias("vec"))


# --- contrast ----------------------------------------------------------------


def snapshots(df: DataFrame, table: str, key: str, rows: int = 32, seed: str = "snap") -> DataFrame:
    """Two disjoint samples of each table's rows (``snap`` 0 and 1), half of the rows at most in each."""
    w = Window.partitionBy(table)
    r = F.row_number().over(w.orderBy(det.text(seed, F.col(key)), key))
    n = F.least(F.lit(rows), F.floor(F.count("*").over(w) / 2))
    return df.withColumn("_r", r).withColumn("_n", n).where(F.col("_r") <= 2 * F.col("_n")).withColumn("snap", (F.col("_r") > F.col("_n")).cast("int")).drop("_r", "_n")


def batches(pool_df: DataFrame, size: int = 512, seed: str = "batch") -> DataFrame:
    """A batch for each column key by hash, about ``size`` vectors each, so the square of pairs stays bounded."""
    n = pool_df.select("table_id", "col_id").distinct().count()
    return pool_df.withColumn("batch", det.pick(max(1, -(-2 * n // size)), seed, F.col("table_id"), F.col("col_id")))


def contrast_loss(pool_df: DataFrame, tau: float = 0.07) -> DataFrame:
    """(batch, table_id, col_id, snap, loss): -sim+/tau plus the log-sum-exp over all others of the batch, the anchor left out."""
    a, b = pool_df.alias("a"), pool_df.alias("b")
    dot = F.aggregate(F.zip_with("a.vec", "b.vec", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x) / tau
    same = (F.col("a.table_id") == F.col("b.table_id")) & (F.col("a.col_id") == F.col("b.col_id"))
    pairs = a.join(b, (F.col("a.batch") == F.col("b.batch")) & ~(same & (F.col("a.snap") == F.col("b.snap")))).select("a.batch", "a.table_id", "a.col_id", "a.snap", dot.alias("s"), same.alias("pos"))
    g = pairs.groupBy("batch", "table_id", "col_id", "snap").agg(F.max("s").alias("top"), F.collect_list("s").alias("all"), F.max(F.when(F.col("pos"), F.col("s"))).alias("plus"))
    lse = F.col("top") + F.log(F.aggregate("all", F.lit(0.0), lambda acc, x: acc + F.exp(x - F.col("top"))))
    return g.where("plus is not null").select("batch", "table_id", "col_id", "snap", (lse - F.col("plus")).alias("loss"))


def fit_head(pool_df: DataFrame, steps: int = 20, rate: float = 0.5, tau: float = 0.2, d: int = D) -> tuple[np.ndarray, list[float]]:
    """A linear head trained on the contrastive loss: gradients of each batch on the executors, their sum on the driver."""
    head, history = np.eye(d), []
    # One row a batch; a batch's size is bounded by ``batches``.
    packed = pool_df.groupBy("batch").agg(F.array_sort(F.collect_list(F.struct("table_id", "col_id", "snap", "vec"))).alias("items")).cache()
    n = pool_df.count()
    for _ in range(steps):
        w = head

        def gradient(frames, w=w):
            for pdf in frames:
                for items in pdf["items"]:
                    x = np.array([list(i["vec"]) for i in items])
                    keys = [(i["table_id"], i["col_id"]) for i in items]
                    plus = np.array([next((j for j, o in enumerate(keys) if o == k and j != i), -1) for i, k in enumerate(keys)])
                    loss, grad = batch_gradient(x, plus, w, tau)
                    yield pd.DataFrame({"loss": [loss], "grad": [grad.ravel().tolist()]})

        rows = packed.select("items").mapInPandas(gradient, "loss double, grad array<double>")
        # One sum: position 0 holds the loss, the others the d×d gradient.
        sums = rows.select(F.posexplode(F.concat(F.array("loss"), "grad")).alias("i", "g")).groupBy("i").agg(F.sum("g").alias("g")).collect()
        g = np.zeros(d * d + 1)
        for r in sums:
            g[r.i] = r.g
        history.append(float(g[0]) / n)
        g = g[1:]
        head = head - rate * g.reshape(d, d) / n
    packed.unpersist()
    return head, history


def batch_gradient(x: np.ndarray, plus: np.ndarray, w: np.ndarray, tau: float) -> tuple[float, np.ndarray]:
    """Summed loss of a batch and its gradient for the head ``w`` (vectors are x @ w, scaled to unit length)."""
    y = x @ w
    norm = np.maximum(np.linalg.norm(y, axis=1, keepdims=True), 1e-9)
    u = y / norm
    s = u @ u.T / tau
    np.fill_diagonal(s, -np.inf)
    p = softmax(s)
    anchors = np.flatnonzero(plus >= 0)
    top = s[anchors].max(1)
    loss = float((top + np.log(np.exp(s[anchors] - top[:, None]).sum(1)) - s[anchors, plus[anchors]]).sum())
    ds = np.zeros_like(p)
    ds[anchors] = p[anchors]
    ds[anchors, plus[anchors]] -= 1
    du = (ds + ds.T) @ u / tau
    dy = (du - u * (u * du).sum(1, keepdims=True)) / norm
    return loss, x.T @ dy


# --- search ------------------------------------------------------------------


def nearest(queries: DataFrame, items: DataFrame, k: int, block: int = 50_000) -> DataFrame:
    """(q, vec_id, score, rk): exact top-k by dot product for stated queries against all items.

    Queries travel in blocks of a fixed size, one pass over the items each; every
    partition keeps its k best per query before the final ranking.
    """
    shape = "q long, vec_id long, score double"
    blocks = max(1, -(-queries.count() // block))

    def one(number: int) -> DataFrame:
        got = queries.where(F.pmod(F.xxhash64("q"), F.lit(blocks)) == number).collect()
        ids, mat = np.array([r.q for r in got], np.int64), np.array([list(r["query"]) for r in got], np.float64)

        def best(frames):
            for pdf in frames:
                if not len(pdf) or not len(ids):
                    continue
                x, vec_ids = np.stack(pdf.embedding.to_numpy()).astype(np.float64), pdf.vec_id.to_numpy()
                s = mat @ x.T
                s[ids[:, None] == vec_ids[None, :]] = -np.inf
                for i, q in enumerate(ids):
                    # All that reach the k-th best score stay, so ties are settled by the final ranking.
                    cut = np.partition(s[i], -min(k, len(x)))[-min(k, len(x))]
                    keep = np.flatnonzero((s[i] >= cut - 1e-6) & np.isfinite(s[i]))
                    yield pd.DataFrame({"q": int(q), "vec_id": vec_ids[keep], "score": s[i][keep]})

        return items.select("vec_id", "embedding").mapInPandas(best, shape)

    found = one(0)
    for number in range(1, blocks):
        found = found.unionByName(one(number))
    w = Window.partitionBy("q").orderBy(F.desc(F.round("score", 6)), "vec_id")
    return found.withColumn("rk", F.row_number().over(w).cast("long")).where(F.col("rk") <= k)


# --- prompt and alignment tasks ----------------------------------------------


def hybrid_prompt(cells: DataFrame, prof: DataFrame, n_values: int = 3, slot: str = "<vec>") -> DataFrame:
    """(table_id, prompt): the table's name, then each column as qualified name, slot, type and key flag, with a few sample values in brackets."""
    values = cells.where(~missing(F.col("value"))).select("table_id", "col_id", "value").distinct()
    ranked = values.withColumn("r", F.row_number().over(Window.partitionBy("table_id", "col_id").orderBy(F.md5("value"), "value"))).where(F.col("r") <= n_values)
    shown = ranked.groupBy("table_id", "col_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("r", "value"))), lambda x: x["value"]), ", ").alias("vals"))
    flag = F.when(F.col("is_key"), F.lit("key")).otherwise("")
    col = F.concat("table_id", F.lit("."), "col_name", F.lit("("), F.concat_ws("|", F.lit(slot), F.col("dtype"), flag), F.lit(")|["), F.coalesce("vals", F.lit("")), F.lit("]"))
    lines = prof.join(shown, ["table_id", "col_id"], "left").select("table_id", F.struct("col_id", col.alias("t")).alias("c"))
    return lines.groupBy("table_id").agg(F.concat(F.lit("table "), F.first("table_id"), F.lit(", columns=["), F.array_join(F.transform(F.array_sort(F.collect_list("c")), lambda c: c["t"]), ", "), F.lit("]")).alias("prompt"))


def splice(prompts: DataFrame, vecs: DataFrame, slot: str = "<vec>") -> DataFrame:
    """(table_id, parts): text and vector parts in turn; the n-th slot takes the n-th column's vectors; markers at both ends."""
    by = vecs.groupBy("table_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("col_id", "vecs"))), lambda x: x["vecs"]).alias("vs"))
    part = lambda kind, text, v: F.struct(F.lit(kind).alias("kind"), text.alias("text"), v.alias("vec"))
    none = F.lit(None).cast("array<array<double>>")
    texts = F.split("prompt", F.lit(slot))
    body = F.flatten(F.transform(texts, lambda x, i: F.when(i < F.size("vs"), F.array(part("text", x, none), part("vec", F.lit(""), F.get("vs", i)))).otherwise(F.array(part("text", x, none)))))
    ends = lambda name: F.array(part("mark", F.lit(name), none))
    return prompts.join(by, "table_id").select("table_id", F.concat(ends("<tab>"), body, ends("</tab>")).alias("parts"))


# Scenarios of joint training: what is trained, and which path samples with tables take.
TRAIN_PLANS = {"encoder_only": (True, False, "table"), "decoder_only": (False, True, "text"), "joint": (True, True, "table")}


def train_plans(spark) -> DataFrame:
    """(plan, part, trained, route): which part each scenario trains and which it freezes; metadata only."""
    rows = [(p, part, on, path) for p, (enc, dec, path) in TRAIN_PLANS.items() for part, on in (("encoder", enc), ("adapter", enc), ("decoder", dec))]
    return spark.createDataFrame(rows, "plan string, part string, trained boolean, route string")


TASKS = ["column_prediction", "cell_prediction", "question_generation", "titling", "row_summary"]

INSTRUCTIONS = {
    "column_prediction": ["Which column holds the value", "Name the column of the value"],
    "cell_prediction": ["Give a value of the column", "Fill in one cell of the column"],
    "question_generation": ["Ask a question that this answers", "Write the question behind this answer"],
    "titling": ["Give the table a title", "Name this table"],
    "row_summary": ["Sum up the row", "Describe this row in a sentence"],
}


def alignment(cells: DataFrame, task: str, rate: float = 0.05, seed: str = "align") -> DataFrame:
    """(sample_id, instruction, input, output) of one task; cells or rows are drawn by hash, the instruction too."""
    u = det.unit(seed, F.lit(task), F.col("table_id"), F.col("row_id"), F.col("col_id"))
    rows = cells.groupBy("table_id", "row_id").agg(F.array_sort(F.collect_list(F.struct("col_id", "col_name", "value"))).alias("cs")).withColumn("col_id", F.lit(-1))
    if task == "column_prediction":
        s = cells.where((u < rate) & ~missing(F.col("value"))).select("table_id", "row_id", "col_id", F.col("value").alias("input"), F.col("col_name").alias("output"))
    elif task == "cell_prediction":
        s = cells.where((u < rate) & ~missing(F.col("value"))).select("table_id", "row_id", "col_id", F.col("col_name").alias("input"), F.col("value").alias("output"))
    elif task == "question_generation":
        key = cells.where("col_id = 0").select("table_id", "row_id", F.col("value").alias("key"))
        s = cells.where((u < rate) & (F.col("col_id") > 0) & ~missing(F.col("value"))).join(key, ["table_id", "row_id"]).select("table_id", "row_id", "col_id", F.col("value").alias("input"), F.concat(F.lit("What is the "), "col_name", F.lit(" of "), "table_id", F.lit(" "), "key", F.lit("?")).alias("output"))
    elif task == "titling":
        s = cells.where("col_id = 0").groupBy("table_id").agg(F.count("*").alias("n"), F.min("col_name").alias("k")).select("table_id", F.lit(0).cast("long").alias("row_id"), F.lit(-1).alias("col_id"), F.col("k").alias("input"), F.concat("table_id", F.lit(" by "), "k").alias("output"))
    elif task == "row_summary":
        text = F.array_join(F.transform("cs", lambda c: F.concat(c["col_name"], F.lit(" is "), F.coalesce(c["value"], F.lit("unknown")))), ", ")
        s = rows.where(u < rate).select("table_id", "row_id", "col_id", F.concat("table_id", F.lit(" row "), F.col("row_id").cast("string")).alias("input"), text.alias("output"))
    else:
        raise ValueError(task)
    options = INSTRUCTIONS[task]
    chosen = F.get(F.array(*map(F.lit, options)), det.pick(len(options), "instruction", F.lit(task), F.col("table_id"), F.col("row_id"), F.col("col_id")))
    return s.select(F.concat_ws("/", F.lit(task), "table_id", F.col("row_id").cast("string"), F.col("col_id").cast("string")).alias("sample_id"), chosen.alias("instruction"), "input", "output")


def route(samples: DataFrame, mode: str = "encoder_decoder") -> DataFrame:
    """Text samples take the text path; samples with tables take the table path unless only the decoder is used."""
    return samples.withColumn("route", F.when((F.size("table_ids") > 0) & F.lit(mode != "decoder_only"), "table").otherwise("text"))


def token_cost(cells: DataFrame, k: int = 4) -> DataFrame:
    """Words of a table written out against k vectors a column."""
    words = F.size(F.split(F.trim(F.coalesce("value", F.lit(""))), r"\s+"))
    return cells.groupBy("table_id").agg(F.sum(words).alias("text_tokens"), (F.countDistinct("col_id") * k).alias("vector_tokens"))
