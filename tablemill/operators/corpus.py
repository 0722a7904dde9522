"""Curation of text corpora: deduplication, tags, filters, token selection, mixing and packing."""

from __future__ import annotations

import math
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.functions.lineage import cut
from tablemill.functions.text import FUNCTION_WORDS, count_matches, let, lines, ngrams, share, shingles, tokens

# --- deduplication -----------------------------------------------------------


def exact(docs: DataFrame, key: Column | None = None) -> DataFrame:
    """doc_id of the first of each group of equal texts, with the number of copies. Only hashes are shuffled."""
    key = F.md5("text") if key is None else key
    return docs.groupBy(key.alias("fingerprint")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("n_copies"))


def minhash_signatures(sets: DataFrame, permutations: int = 128, seed: str = "minhash") -> DataFrame:
    """(doc_id, sig): minimum of each seeded permutation over the 31-bit parts of a document's shingle hashes, one Arrow batch at a time."""
    prime = (1 << 31) - 1
    coefficient = [(_seeded(f"{seed}-a-{i}", prime - 1) + 1, _seeded(f"{seed}-b-{i}", prime)) for i in range(permutations)]

    def run(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                lists = part.column(1)
                ends = lists.offsets.to_numpy().astype(np.int64)
                h = lists.values.to_numpy()[ends[0] : ends[-1]] & prime
                sig = np.empty((part.num_rows, permutations), np.int64)
                for i, (a, b) in enumerate(coefficient):
                    sig[:, i] = np.minimum.reduceat((h * a + b) % prime, ends[:-1] - ends[0])  # no set is empty
                cuts = pa.array(np.arange(part.num_rows + 1, dtype=np.int32) * permutations)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(cuts, pa.array(sig.ravel()))], names=["doc_id", "sig"])

    return sets.select(F.col("doc_id").cast("long"), "set").mapInArrow(run, "doc_id long, sig array<long>")


def _seeded(key: str, below: int) -> int:
    from hashlib import md5

    return int(md5(key.encode()).hexdigest()[:15], 16) % below


def near_groups(docs: DataFrame, threshold: float = 0.8, bands: int = 32, rows: int = 4, width: int = 5) -> DataFrame:
    """(doc_id, class_id): classes of documents whose shingle sets are ``threshold`` alike, by banded MinHash.

    Equal texts meet first, so a group of copies is one row. Documents that share a
    band are candidates; ``alike`` links them on their exact sets. A class is named
    by its least id.
    """
    kept = docs.select("doc_id", F.md5(F.coalesce("text", F.lit(""))).alias("fp"), "text")
    classes = kept.groupBy("fp").agg(F.min("doc_id").alias("rep"))
    members = kept.select("doc_id", "fp").join(classes, "fp").select("doc_id", "rep")
    reps = docs.join(classes.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi").dropDuplicates(["doc_id"]).select("doc_id", tokens(F.lower("text")).alias("words"))
    sets = cut(reps.select("doc_id", F.transform(shingles(F.col("words"), width), lambda s: F.xxhash64(s)).alias("set")))
    banded = cut(minhash_signatures(sets, bands * rows).select("doc_id", F.posexplode(F.array(*[F.xxhash64(F.slice("sig", 1 + i * rows, rows)) for i in range(bands)])).alias("band", "h")))
    shared = banded.groupBy("band", "h").agg(F.min("doc_id").alias("x"), F.max("doc_id").alias("top")).where("x < top").select("band", "h")
    near = banded.join(shared, ["band", "h"], "left_semi").select("doc_id").distinct()
    root = components(alike(cut(sets.join(near, "doc_id", "left_semi")), threshold))
    return members.join(root.select(F.col("node").alias("rep"), "root"), "rep", "left").select("doc_id", F.coalesce("root", "rep").alias("class_id"))


def prefixes(sets: DataFrame, threshold: float) -> DataFrame:
    """(key, doc_id, size, own, place): the rarest shingles of each set (doc_id, set) that another has, as far as its prefix reaches.

    Two sets that are alike enough share one of their first ``size - threshold *
    size + 1`` shingles in order of frequency. ``own`` counts those no other set has;
    they come first and pair with nothing. ``place`` counts what precedes the key.
    """
    each = sets.select("doc_id", F.size("set").alias("size"), F.explode("set").alias("key"))
    common = each.groupBy("key").agg(F.count("*").alias("times")).where("times > 1")
    ranked = each.join(common, "key").groupBy("doc_id", "size").agg(F.sort_array(F.collect_list(F.struct("times", "key"))).alias("common"))
    own = F.col("size") - F.size("common")
    reach = F.col("size") - F.ceil(F.lit(threshold) * F.col("size") - 1e-6) + 1 - own
    at = F.posexplode(F.slice("common", F.lit(1), F.greatest(F.lit(0), reach).cast("int"))).alias("at", "s")
    return ranked.select("doc_id", "size", own.alias("own"), at).select(F.col("s.key").alias("key"), "doc_id", "size", "own", (F.col("own") + F.col("at")).alias("place"))


def alike(sets: DataFrame, threshold: float) -> DataFrame:
    """(x, y): links of sets with a Jaccard similarity of ``threshold`` or more, enough to hold all components together.

    The member of a bucket with the fewest shingles of its own is compared with the
    others first. What still stands apart is compared only where sizes, and the place
    of the rarest shingle in common, leave room for the overlap needed.
    """
    members = cut(prefixes(sets, threshold))
    of = lambda m, c: F.col(f"{m}.{c}")

    def room(x, y):
        need = F.ceil(F.lit(threshold / (1 + threshold)) * (of(x, "size") + of(y, "size")) - 1e-6)
        return (F.least(of(x, "size") - of(x, "place"), of(y, "size") - of(y, "place")) >= need) & (F.least(of(x, "size") - of(x, "own"), of(y, "size") - of(y, "own")) >= need)

    def verified(pairs: DataFrame) -> DataFrame:
        both = pairs.join(sets.select(F.col("doc_id").alias("x"), F.col("set").alias("xs")), "x").join(sets.select(F.col("doc_id").alias("y"), F.col("set").alias("ys")), "y")
        common = F.size(F.array_intersect("xs", "ys"))
        return cut(both.where(common >= threshold * (F.size("xs") + F.size("ys") - common)).select("x", "y"))

    def paired(m: DataFrame, p: DataFrame, apart: Column) -> DataFrame:
        met = m.alias("m").join(p.alias("p"), (of("m", "key") == of("p", "key")) & apart & room("m", "p"))
        return verified(met.select(F.least("m.doc_id", "p.doc_id").alias("x"), F.greatest("m.doc_id", "p.doc_id").alias("y")).distinct())

    pivots = members.groupBy("key").agg(F.min(F.struct("own", "doc_id", "size", "place")).alias("p"), F.count("*").alias("n")).where("n > 1").select("key", "p.*")
    links = paired(members, pivots, of("m", "doc_id") != of("p", "doc_id"))
    root = components(links)
    named = members.join(root.select(F.col("node").alias("doc_id"), "root"), "doc_id", "left").withColumn("root", F.coalesce("root", "doc_id"))
    several = named.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("top")).where("low < top").select("key")
    left = cut(named.join(several, "key", "left_semi"))
    return links.unionByName(paired(left, left, (of("m", "doc_id") < of("p", "doc_id")) & (of("m", "root") != of("p", "root"))))


def components(links: DataFrame) -> DataFrame:
    """(node, root) of the undirected links (x, y): least node of each component, by min-label rounds with pointer jumping."""
    both = cut(links.select("x", "y").unionByName(links.select(F.col("y").alias("x"), F.col("x").alias("y"))).distinct())
    now = cut(both.groupBy(F.col("x").alias("node")).agg(F.least(F.min("y"), F.first("x")).alias("root")))
    while True:
        near = both.join(now.select(F.col("node").alias("y"), "root"), "y").groupBy(F.col("x").alias("node")).agg(F.min("root").alias("low"))
        new = now.join(near, "node").select("node", F.least("root", "low").alias("root"))
        jump = new.select(F.col("node").alias("root"), F.col("root").alias("next"))
        new = cut(new.join(jump, "root", "left").select("node", F.coalesce("next", "root").alias("root")))
        changed = new.join(now.withColumnRenamed("root", "old"), "node").where("root <> old").limit(1).count()
        now = new
        if not changed:
            return now


def repeated_lines(docs: DataFrame, min_docs: int = 2, min_chars: int = 10) -> DataFrame:
    """Lines of ``min_chars`` and more that stand in several documents, by hash, with their first document."""
    at = docs.select("doc_id", F.explode(F.array_distinct(lines(F.col("text")))).alias("line")).where(F.length("line") >= min_chars)
    return at.groupBy(F.md5("line").alias("line_hash")).agg(F.min("doc_id").alias("first_doc"), F.count("*").alias("n_docs")).where(F.col("n_docs") >= min_docs)


# --- tags --------------------------------------------------------------------


def language_scores(text: Column) -> dict[str, Column]:
    """Share of function words of each language; the words are cut once for all of them."""

    def score(words, known):
        return share(F.size(F.filter(words, lambda w: w.isin(known))).cast("double"), F.size(words))

    every = let(tokens(F.lower(text)), lambda words: F.array(*[score(words, known) for known in FUNCTION_WORDS.values()]))
    return {lang: every[i] for i, lang in enumerate(FUNCTION_WORDS)}


def basic_tags(docs: DataFrame) -> DataFrame:
    """The printed tags of prose: words per line, fertility, repetition ratio, language score."""
    base = docs.select("doc_id", "text", lines(F.col("text")).alias("ls"), tokens(F.col("text")).alias("ws"))
    words = F.transform("ls", lambda x: F.size(tokens(x)))
    base = base.withColumn("lw", words)
    scores = language_scores(F.col("text"))
    return base.select(
        "doc_id",
        F.array_join(F.col("lw").cast("array<string>"), ",").alias("lines_num_words"),
        F.array_min("lw").alias("min_line_words"), F.array_max("lw").alias("max_line_words"),
        (F.aggregate("lw", F.lit(0), lambda a, x: a + x) / F.size("lw")).alias("mean_line_words"),
        share(F.length("text").cast("double"), F.size("ws")).alias("fertility"),
        (1 - F.size(F.array_distinct("ls")) / F.size("ls")).alias("repetition_ratio"),
        F.greatest(*scores.values()).alias("language_score"),
    )


def tag_columns(text: Column, ws: Column, ls: Column, wh: Column | None = None) -> dict[str, Column]:
    """All other tags in groups: length, characters, lines, repetition, language, content, code. ``wh``: hashes of the words."""
    wh = F.transform(ws, lambda w: F.xxhash64(w)) if wh is None else wh
    n = F.length(text)

    def chars(pattern):
        return share(count_matches(text, pattern).cast("double"), n)

    def line_share(cond):
        return F.size(F.filter(ls, cond)) / F.size(ls)

    def dup_grams(k):
        return let(hash_grams(wh, k), lambda g: share((F.size(g) - F.size(F.array_distinct(g))).cast("double"), F.size(g)))

    def top_gram(k):
        return let(hash_grams(wh, k), lambda g: share(F.array_max(run_lengths(g)).cast("double"), F.size(g)))

    words_len = F.transform(ws, lambda w: F.length(w))
    line_len = F.transform(ls, lambda x: F.length(x))
    mean = lambda a: share(F.aggregate(a, F.lit(0), lambda s, x: s + x).cast("double"), F.size(a))
    scores = language_scores(text)
    ranked = F.sort_array(F.array(*[F.coalesce(x, F.lit(0.0)) for x in scores.values()]), asc=False)
    stop = [w for ws_ in FUNCTION_WORDS.values() for w in ws_]
    n_stop = F.size(F.filter(ws, lambda w: F.lower(w).isin(stop)))
    comment = r"^\s*(#|--|//)"
    return {
        # length
        "n_chars": n.cast("long"), "n_words": F.size(ws).cast("long"), "n_lines": F.size(ls).cast("long"),
        "n_paragraphs": (count_matches(text, r"\n\n+") + 1).cast("long"), "n_sentences": count_matches(text, r"[.!?]+(\s|$)"),
        "mean_word_len": mean(words_len), "max_word_len": F.array_max(words_len), "mean_line_len": mean(line_len), "max_line_len": F.array_max(line_len),
        # characters
        "alpha_frac": chars(r"\pL"), "digit_frac": chars(r"[0-9]"), "upper_frac": chars(r"\p{Lu}"), "space_frac": chars(r"\s"),
        "punct_frac": chars(r"[!-/:-@\[-`{-~]"), "nonascii_frac": chars(r"[^\x00-\x7F]"), "symbol_word_ratio": share(count_matches(text, r"[#*|~^]").cast("double"), F.size(ws)),
        "bracket_frac": chars(r"[(){}\[\]]"), "control_char_count": count_matches(text, r"[\x00-\x08\x0E-\x1F]"),
        # lines
        "terminal_punct_line_frac": line_share(lambda x: x.rlike(r"[.!?]\s*$")), "bullet_line_frac": line_share(lambda x: x.rlike(r"^\s*[-*•]")),
        "ellipsis_line_frac": line_share(lambda x: x.rlike(r"(\.\.\.|…)\s*$")), "short_line_frac": line_share(lambda x: F.length(x) < 20), "empty_line_frac": line_share(lambda x: F.trim(x) == ""),
        "pipe_line_frac": line_share(lambda x: x.contains("|")), "long_line_count": F.size(F.filter(ls, lambda x: F.length(x) > 1000)),
        "dup_line_char_frac": share((F.aggregate(line_len, F.lit(0), lambda s, x: s + x) - F.aggregate(F.transform(F.array_distinct(ls), lambda x: F.length(x)), F.lit(0), lambda s, x: s + x)).cast("double"), F.aggregate(line_len, F.lit(0), lambda s, x: s + x)),
        # repetition
        "top2gram_frac": top_gram(2), "top3gram_frac": top_gram(3), "top4gram_frac": top_gram(4), "dup5gram_frac": dup_grams(5), "dup10gram_frac": dup_grams(10),
        "uniq_word_frac": share(F.size(F.array_distinct(ws)).cast("double"), F.size(ws)),
        "word_entropy": _entropy(wh),
        # language
        "stopword_count": n_stop.cast("long"), "stopword_frac": share(n_stop.cast("double"), F.size(ws)), "lang_margin": ranked[0] - ranked[1],
        # content
        "url_count": count_matches(text, r"https?://"), "email_count": count_matches(text, r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+\.[A-Za-z0-9.-]+"), "number_count": count_matches(text, r"[0-9]+"),
        "license_line": F.exists(ls, lambda x: x.rlike(r"(?i)licen[sc]ed? under|all rights reserved|under the mit license")), "boilerplate_hits": count_matches(text, r"(?i)cookie|privacy policy|terms of use|javascript|lorem ipsum"), "keyword_hits": count_matches(text, r"(?i)\b(kill|hate|porn|bomb)\b"),
        # code
        "comment_line_frac": line_share(lambda x: x.rlike(comment)), "has_docstring": text.contains('"""'), "import_count": F.size(F.filter(ls, lambda x: x.rlike(r"^\s*(import|from) "))).cast("long"),
        "def_count": F.size(F.filter(ls, lambda x: x.rlike(r"^\s*(def|class|function) "))).cast("long"), "autogenerated": F.exists(F.slice(ls, 1, 5), lambda x: F.lower(x).rlike("auto-?generated|do not edit")), "encoded_blob": text.rlike(r"[A-Za-z0-9+/=]{1000}"),
    }


def hash_grams(wh: Column, k: int) -> Column:
    """A hash of each run of k word hashes; none if there are fewer words."""
    none = F.expr("cast(array() as array<bigint>)")
    return let(wh, lambda h: F.when(F.size(h) >= k, F.transform(F.sequence(F.lit(1), F.size(h) - (k - 1)), lambda i: F.xxhash64(F.slice(h, i, k)))).otherwise(none))


def run_lengths(values: Column) -> Column:
    """How often each distinct value occurs, by the borders of the sorted array."""
    none = F.expr("cast(array() as array<int>)")

    def lengths(s):
        borders = F.filter(F.sequence(F.lit(0), F.size(s) - 1), lambda i: (i == 0) | (F.get(s, i) != F.get(s, i - 1)))
        return let(borders, lambda b: F.transform(b, lambda p, j: F.coalesce(F.get(b, j + 1), F.size(s)) - p))

    return let(F.sort_array(values), lambda s: F.when(F.size(s) > 0, lengths(s)).otherwise(none))


def _entropy(wh: Column) -> Column:
    """Bits of the word distribution: log2 n - sum(c log2 c) / n over the counts of the words."""
    n = F.size(wh)
    return F.when(n > 0, F.log2(n.cast("double")) - F.aggregate(run_lengths(wh), F.lit(0.0), lambda a, c: a + _clog(c)) / n)


def _clog(c: Column) -> Column:
    return F.when(c > 0, c * F.log2(c.cast("double"))).otherwise(F.lit(0.0))


def all_tags(docs: DataFrame) -> DataFrame:
    base = docs.select("doc_id", "text", tokens(F.col("text")).alias("ws"), lines(F.col("text")).alias("ls")).withColumn("wh", F.transform("ws", lambda w: F.xxhash64(w)))
    return base.select("doc_id", *[c.alias(k) for k, c in tag_columns(F.col("text"), F.col("ws"), F.col("ls"), F.col("wh")).items()])


# --- filters -----------------------------------------------------------------

POLICY = [
    ("too_short", lambda: F.size("ws") < 5),
    ("too_long_line", lambda: F.exists("ls", lambda x: F.length(x) > 100000)),
    ("repeated", lambda: F.col("repetition_ratio") > 0.3),
    ("pipe_lines", lambda: F.size(F.filter("ls", lambda x: x.contains("|"))) / F.size("ls") > 0.5),
    ("symbol_heavy", lambda: F.col("symbol_ratio") > 0.3),
    ("low_language", lambda: F.coalesce(F.col("language_score"), F.lit(0.0)) < 0.05),
    ("license_line", lambda: F.lower("text").rlike("licensed under|rights reserved|mit license")),
]


def decide(docs: DataFrame) -> DataFrame:
    """keep, the first reason and all reasons of the ordered policy."""
    base = docs.select("doc_id", "text", tokens(F.col("text")).alias("ws"), lines(F.col("text")).alias("ls")).withColumns({
        "repetition_ratio": 1 - F.size(F.array_distinct("ls")) / F.size("ls"),
        "symbol_ratio": share(count_matches(F.col("text"), r"[#*|~^!]").cast("double"), F.size("ws")),
        "language_score": F.greatest(*language_scores(F.col("text")).values()),
    })
    hits = F.array_compact(F.array(*[F.when(rule(), F.lit(name)) for name, rule in POLICY]))
    return base.select("doc_id", (F.size(hits) == 0).alias("keep"), F.get(hits, F.lit(0)).alias("reason"), F.array_join(hits, ",").alias("reasons"))


def web_rules(docs: DataFrame) -> DataFrame:
    """Line rules, then page rules, for prose from the web: kept lines, sentences, and whether the page stays."""
    good = F.filter(lines(F.col("text")), lambda x: x.rlike(r"""[.!?"]\s*$""") & (F.size(tokens(x)) >= 5) & ~F.lower(x).rlike("javascript|cookie|privacy policy|terms of use"))
    kept = F.array_join(good, "\n")
    made = docs.select("doc_id", F.size(lines(F.col("text"))).cast("long").alias("n_lines"), F.size(good).cast("long").alias("n_kept"), kept.alias("kept"))
    sentences = count_matches(F.col("kept"), r"[.!?]+(\s|$)")
    return made.select("doc_id", "n_lines", "n_kept", sentences.alias("n_sentences"), ((sentences >= 3) & ~F.col("kept").contains("{") & ~F.lower("kept").contains("lorem ipsum")).alias("keep"))


def strip_html(html: Column) -> Column:
    """Text of a page: scripts, styles and comments out, block ends as newlines, tags out, common entities read."""
    s = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    s = F.regexp_replace(s, r"(?s)<!--.*?-->", " ")
    s = F.regexp_replace(s, r"(?i)<(br|/p|/li|/h[1-6]|/div|/tr)[^>]*>", "\n")
    s = F.regexp_replace(s, r"<[^>]*>", " ")
    for name, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&amp;", "&")):
        s = F.replace(s, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(F.regexp_replace(s, r"[ \t]+", " "), r" ?\n[ \n]*", "\n"))


def page_rules(pages: DataFrame) -> DataFrame:
    """URL, extraction and repetition rules over web pages."""
    made = pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), "url", strip_html(F.col("html")).alias("text"))
    ls = F.filter(lines(F.col("text")), lambda x: F.length(x) > 0)
    made = made.withColumn("ls", ls)
    bad_url = F.lower("url").rlike("casino|porn|bet|adult")
    repeated = share((F.size("ls") - F.size(F.array_distinct("ls"))).cast("double"), F.size("ls"))
    return made.select(
        "page_id", "host", F.size("ls").cast("long").alias("n_lines"), F.length("text").cast("long").alias("n_chars"), repeated.alias("repeated"),
        F.when(bad_url, "url").when(F.length("text") < 200, "short").when(repeated > 0.3, "repeated").otherwise("ok").alias("verdict"),
    )


def keyword_hits(docs: DataFrame, words: list[str]) -> DataFrame:
    """Documents with whole-word hits and the distinct words found."""
    found = F.array_intersect(F.transform(tokens(F.lower("text")), lambda w: F.regexp_replace(w, "[.,!?;:]+$", "")), F.array(*map(F.lit, words)))
    return docs.select("doc_id", F.size(found).alias("n_hits"), F.array_join(F.array_sort(found), ",").alias("hits")).where("n_hits > 0")


def code_rules(code: DataFrame) -> DataFrame:
    """Line length, letters, generated marks and blobs in code."""
    ls = lines(F.col("text"))
    longest = F.array_max(F.transform(ls, lambda x: F.length(x)))
    mean = F.length("text") / F.size(ls)
    alnum = share(count_matches(F.col("text"), "[A-Za-z0-9]").cast("double"), F.length("text"))
    generated = F.exists(F.slice(ls, 1, 5), lambda x: F.lower(x).contains("auto-generated"))
    return code.select("code_id", (longest <= 1000).alias("line_ok"), (mean <= 100).alias("mean_ok"), (alnum >= 0.25).alias("alnum_ok"), (~generated).alias("hand_ok"), (~F.col("text").rlike("[A-Za-z0-9+/=]{1000}")).alias("blob_ok"))


def nl_ratio(text: Column) -> Column:
    """Share of comment and docstring characters in code."""
    marks = F.regexp_extract_all(text, F.lit(r"(?s)\"\"\".*?\"\"\"|#[^\n]*|--[^\n]*"), F.lit(0))
    return share(F.aggregate(F.transform(marks, lambda m: F.length(m)), F.lit(0), lambda s, x: s + x).cast("double"), F.length(text))


def decontaminate(docs: DataFrame, bench: DataFrame, n: int = 8) -> DataFrame:
    """(doc_id, n_items): documents that share an n-gram of words with a test passage. The grams of the tests are hashed;
    Spark broadcasts them while they are small and shuffles by hash otherwise."""
    grams = bench.select(F.explode(ngrams(tokens(F.lower("text")), n)).alias("g"), "item_id").select(F.xxhash64("g").alias("h"), "g", "item_id").distinct()
    own = docs.select("doc_id", F.explode(F.array_distinct(ngrams(tokens(F.lower("text")), n))).alias("g")).select("doc_id", F.xxhash64("g").alias("h"), "g")
    return own.join(grams, ["h", "g"]).groupBy("doc_id").agg(F.countDistinct("item_id").alias("n_items"))


# --- token selection ---------------------------------------------------------


def token_rows(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", F.posexplode(tokens(F.lower("text"))).alias("pos", "token"))


def fit_unigram(docs: DataFrame) -> DataFrame:
    """(token, n) by partial counts; text is not shuffled."""
    return docs.select(F.explode(tokens(F.lower("text"))).alias("token")).groupBy("token").agg(F.count("*").alias("n"))


def ln(x: Column) -> Column:
    """Logarithm by the C library, as DuckDB has it. The JVM's differs in the last bit of some values, which is enough to
    reorder tokens of equal odds that are ranked by the difference of two logarithms."""

    def run(values: pd.Series) -> pd.Series:
        return pd.Series([math.log(v) for v in values.tolist()], dtype="float64")

    return F.pandas_udf(run, "double")(x)


def losses(current: DataFrame, reference: DataFrame, alpha: float = 1.0) -> DataFrame:
    """(token, loss_cur, loss_ref): add-alpha unigram losses over the current corpus' vocabulary."""
    both = current.select("token", F.col("n").alias("c")).join(reference.select("token", F.col("n").alias("r")), "token", "left").withColumn("r", F.coalesce("r", F.lit(0)))
    total = both.agg(F.sum("c").alias("c"), F.sum("r").alias("r"), F.count("*").alias("v")).first()
    c, r, v = (float(x or 0) for x in total)
    return both.select("token", (-ln((F.col("c") + alpha) / (c + alpha * v))).alias("loss_cur"), (-ln((F.col("r") + alpha) / (r + alpha * v))).alias("loss_ref"))


def excess(docs: DataFrame, labels: DataFrame, alpha: float = 1.0) -> DataFrame:
    """(doc_id, token, n, loss_cur, excess) per distinct token of each document; the reference is fitted on good, harmless text.

    Texts are tokenised once; both models are sums over the counts of each document.
    """
    own = cut(docs.select("doc_id", F.explode(tokens(F.lower("text"))).alias("token")).groupBy("doc_id", "token").agg(F.count("*").alias("n")))
    good = own.join(labels.where("quality = 1 and toxic = 0").select("doc_id").distinct(), "doc_id", "left_semi")
    counted = lambda rows: rows.groupBy("token").agg(F.sum("n").alias("n"))
    table = cut(losses(cut(counted(own)), counted(good), alpha))
    return own.join(table, "token").select("doc_id", "token", "n", "loss_cur", (F.col("loss_cur") - F.col("loss_ref")).alias("excess"))


def excess_in_context(docs: DataFrame, labels: DataFrame, alpha: float = 1.0) -> DataFrame:
    """(doc_id, before, token, n, loss_cur, excess): the same with models of order two, a token given the one before it.

    The first token of a text follows the empty string; a pair's loss is that of its
    token among all that follow the same word, smoothed by ``alpha`` for each word known.
    """
    none = F.expr("cast(array() as array<string>)")
    words = docs.select("doc_id", tokens(F.lower("text")).alias("ws"))
    pairs = words.select("doc_id", F.explode(F.arrays_zip(F.concat(F.array(F.lit("")), F.when(F.size("ws") > 1, F.slice("ws", F.lit(1), F.size("ws") - 1)).otherwise(none)).alias("before"), F.col("ws").alias("token"))).alias("p")).where("p.token is not null")
    own = cut(pairs.groupBy("doc_id", F.col("p.before").alias("before"), F.col("p.token").alias("token")).agg(F.count("*").alias("n")))
    good = own.join(labels.where("quality = 1 and toxic = 0").select("doc_id").distinct(), "doc_id", "left_semi")
    v = float(own.agg(F.countDistinct("token")).first()[0])

    def model(rows: DataFrame, loss: str) -> DataFrame:
        pair = rows.groupBy("before", "token").agg(F.sum("n").alias("c"))
        context = pair.groupBy("before").agg(F.sum("c").alias("t"))
        return pair.join(context, "before").select("before", "token", (-F.log((F.col("c") + alpha) / (F.col("t") + alpha * v))).alias(loss)), context.select("before", (-F.log(F.lit(alpha) / (F.col("t") + alpha * v))).alias(f"{loss}_unseen"))

    current, _ = model(own, "loss_cur")
    reference, unseen = model(good, "loss_ref")
    table = current.join(reference, ["before", "token"], "left").join(unseen, "before", "left")
    table = table.select("before", "token", "loss_cur", F.coalesce("loss_ref", "loss_ref_unseen", F.lit(-1.0) * F.log(F.lit(1.0 / max(v, 1.0)))).alias("loss_ref"))
    return own.join(table, ["before", "token"]).select("doc_id", "before", "token", "n", "loss_cur", (F.col("loss_cur") - F.col("loss_ref")).alias("excess"))


def masked(scored: DataFrame, threshold: float = 0.6, mode: str = "score") -> DataFrame:
    """``keep`` by raw excess, by excess scaled to 0..1 inside the document, by rank share, all, or at random."""
    if mode == "score":
        return scored.withColumn("keep", F.col("excess") >= threshold)
    if mode == "minmax":
        w = Window.partitionBy("doc_id")
        low, high = F.min("excess").over(w), F.max("excess").over(w)
        return scored.withColumn("keep", F.when(high > low, (F.col("excess") - low) / (high - low)).otherwise(0.0) >= threshold)
    if mode == "ratio":
        w = Window.partitionBy("doc_id").orderBy(F.desc("excess"), "token")
        before = F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, -1))
        total = F.sum("n").over(Window.partitionBy("doc_id"))
        return scored.withColumn("keep", F.coalesce(before, F.lit(0)) < threshold * total)
    if mode == "all":
        return scored.withColumn("keep", F.lit(True))
    if mode == "random":
        return scored.withColumn("keep", det.unit("keep", F.col("doc_id"), F.col("token")) < threshold)
    raise ValueError(mode)


def selective_loss(marked: DataFrame) -> DataFrame:
    """Per document: tokens, kept tokens, and the mean loss over the kept ones."""
    kept = F.when(F.col("keep"), F.col("n"))
    return marked.groupBy("doc_id").agg(F.sum("n").alias("n_tokens"), F.coalesce(F.sum(kept), F.lit(0)).alias("n_kept"), F.round(F.sum(F.when(F.col("keep"), F.col("n") * F.col("loss_cur"))) / F.sum(kept), 6).alias("loss"))


# --- mixing and packing ------------------------------------------------------


def to_ratio(rows: DataFrame, kind: str, weight: str, targets: dict[str, float], key: str, seed: str = "mix") -> DataFrame:
    """The largest sample that meets target shares: rows of each kind are kept with the rate its scarcest kind allows."""
    totals = {r[0]: float(r[1]) for r in rows.where(F.col(kind).isin(list(targets))).groupBy(kind).agg(F.sum(weight)).collect()}
    size = min((totals[k] / t for k, t in targets.items() if t > 0 and k in totals), default=0.0)
    rate = F.create_map(*[x for k, t in targets.items() for x in (F.lit(k), F.lit(min(1.0, t * size / totals[k]) if totals.get(k) else 0.0))])
    return rows.where(det.unit(seed, F.col(key)) < F.coalesce(rate[F.col(kind)], F.lit(0.0)))


def prefix_sums(rows: DataFrame, order: str, size: str, per_range: int = 100_000) -> DataFrame:
    """``start``: sum of the sizes before each row in the order of a hexadecimal key.

    Ranges by the key's first digits are summed on their own; only one number a
    range meets in one place, so no task sees all rows. There are as many ranges as
    keep ``per_range`` rows in each, up to 65536.
    """
    ranges = min(65536, max(64, -(-rows.count() // per_range)))
    r = (F.conv(F.substring(order, 1, 4), 16, 10).cast("long") * ranges / 65536).cast("int")
    ranged = rows.withColumn("r", r)
    before = ranged.groupBy("r").agg(F.sum(size).alias("s")).withColumn("base", F.coalesce(F.sum("s").over(Window.orderBy("r").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("r", "base")
    inside = F.coalesce(F.sum(size).over(Window.partitionBy("r").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return ranged.withColumn("inside", inside).join(F.broadcast(before), "r").withColumn("start", F.col("base") + F.col("inside")).drop("r", "base", "inside")


def concat_cut(docs: DataFrame, ctx: int = 8192, seed: str = "pack") -> DataFrame:
    """Shuffle, concatenate, cut: (pack_id, doc_id, from, to) pieces."""
    sized = docs.select("doc_id", F.size(tokens(F.col("text"))).cast("long").alias("n"), det.text(seed, F.col("doc_id")).alias("o")).where("n > 0")
    placed = prefix_sums(sized, "o", "n")
    first, last = F.floor(F.col("start") / ctx), F.floor((F.col("start") + F.col("n") - 1) / ctx)
    cut = placed.withColumn("pack_id", F.explode(F.sequence(first, last)))
    return cut.select("pack_id", "doc_id", F.greatest(F.lit(0), F.col("pack_id") * ctx - F.col("start")).cast("long").alias("from"), F.least("n", (F.col("pack_id") + 1) * ctx - F.col("start")).cast("long").alias("to"))


def by_length(docs: DataFrame, ctx: int = 8192, per_shard: int = 200_000) -> DataFrame:
    """Best-fit-decreasing packs inside shards; only documents longer than ``ctx`` are cut. Shards grow in number, not in size."""
    shards = max(8, -(-docs.count() // per_shard))
    sized = docs.select("doc_id", F.size(tokens(F.col("text"))).cast("long").alias("n")).where("n > 0").withColumn("shard", det.pick(shards, "shard", F.col("doc_id")))

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        import bisect

        rows, room, count = [], [], 0  # room: sorted (free, pack)
        for doc, n in sorted(zip(pdf.doc_id.tolist(), pdf.n.tolist()), key=lambda x: (-x[1], x[0])):
            at = 0
            while n - at >= ctx:
                rows.append((count, doc, at, at + ctx))
                count, at = count + 1, at + ctx
            if n > at:
                i = bisect.bisect_left(room, (n - at, -1))
                free, p = room.pop(i) if i < len(room) else (ctx, count)
                count += p == count
                rows.append((p, doc, at, n))
                if free > n - at:
                    bisect.insort(room, (free - (n - at), p))
        out = pd.DataFrame(rows, columns=["pack", "doc_id", "from", "to"])
        out.insert(0, "shard", int(pdf.shard.iloc[0]))
        return out

    return sized.groupBy("shard").applyInPandas(pack, "shard int, pack long, doc_id long, from long, to long")


def pack_report(packs: DataFrame, *pack: str, ctx: int) -> DataFrame:
    """Packs, fill and documents cut."""
    used = packs.groupBy(*pack).agg(F.sum(F.col("to") - F.col("from")).alias("n"))
    cut = packs.groupBy("doc_id").agg(F.count("*").alias("pieces")).agg(F.count("*").alias("docs"), F.sum((F.col("pieces") > 1).cast("long")).alias("cut_docs"))
    return used.agg(F.count("*").alias("packs"), F.sum("n").alias("tokens"), F.max("n").alias("largest")).crossJoin(F.broadcast(cut)).select("packs", "tokens", "largest", F.round(F.col("tokens") / (F.col("packs") * ctx), 6).alias("fill"), "docs", "cut_docs")


def learning_rate(step: Column, steps: int, peak: float = 3e-5, warmup: float = 0.03) -> Column:
    """Learning rate of a step among ``steps``: linear warm-up, then half a cosine."""
    w = max(1, int(steps * warmup))
    return F.round(F.when(step < w, peak * (step + 1) / w).otherwise(0.5 * peak * (1 + F.cos(F.lit(3.141592653589793) * (step - w) / max(1, steps - w)))), 12)


def cosine_schedule(packs: DataFrame, peak: float = 3e-5, warmup: float = 0.03) -> DataFrame:
    """(step, tokens, lr): one step a pack of (pack_id, doc_id, from, to) pieces, numbered from 0 without gaps."""
    sized = cut(packs.groupBy(F.col("pack_id").alias("step")).agg(F.sum(F.col("to") - F.col("from")).alias("tokens")))
    return sized.select("step", "tokens", learning_rate(F.col("step"), sized.count(), peak, warmup).alias("lr"))


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), frames)
