"""Queries of corpus curation."""

from __future__ import annotations

from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.functions.lineage import cut
from tablemill.functions.text import FUNCTION_WORDS, tokens
from tablemill.operators import corpus as C
from tablemill.operators import samples as S
from tablemill.plans.registry import query

TOK = r"regexp_extract_all(coalesce(text, ''), '\S+')"
LTOK = r"regexp_extract_all(lower(coalesce(text, '')), '\S+')"
SPLIT = "string_split(coalesce(text, ''), chr(10))"


def sql_list(words) -> str:
    return "(" + ", ".join("'" + w.replace("'", "''") + "'" for w in words) + ")"


@query("cpt_assemble", """
SELECT kind, lang, count(*)::BIGINT AS docs, sum(length(text))::BIGINT AS chars FROM
(SELECT 'general' AS kind, lang, text FROM documents UNION ALL SELECT 'dialogue', role, text FROM conversations) GROUP BY kind, lang""")
def cpt_assemble(t):
    parts = C.union_all([t.documents.select(F.lit("general").alias("kind"), "lang", "text"), t.conversations.select(F.lit("dialogue").alias("kind"), F.col("role").alias("lang"), "text")])
    return parts.groupBy("kind", "lang").agg(F.count("*").alias("docs"), F.sum(F.length("text")).alias("chars"))


@query("cpt_numeric_emphasis", r"""
SELECT doc_id, len(regexp_extract_all(text, '[0-9]+'))::BIGINT AS numbers, len(regexp_extract_all(text, '\|'))::BIGINT AS pipes,
       CASE WHEN contains(text, '|') THEN 3 WHEN len(regexp_extract_all(text, '[0-9]+')) >= 2 THEN 2 ELSE 1 END AS weight FROM documents""")
def cpt_numeric_emphasis(t):
    text = F.col("text")
    numbers, pipes = F.regexp_count(text, F.lit("[0-9]+")).cast("long"), F.regexp_count(text, F.lit(r"\|")).cast("long")
    return t.documents.select("doc_id", numbers.alias("numbers"), pipes.alias("pipes"), F.when(text.contains("|"), 3).when(numbers >= 2, 2).otherwise(1).alias("weight"))


@query("cpt_exact_dedup", "SELECT md5(text) AS fingerprint, min(doc_id) AS doc_id, count(*)::BIGINT AS n_copies FROM documents GROUP BY 1")
def cpt_exact_dedup(t):
    return C.exact(t.documents)


@query("cpt_dedup_groups", "SELECT count(*)::BIGINT AS n_groups, sum(n)::BIGINT AS n_rows FROM (SELECT count(*) AS n FROM documents GROUP BY text HAVING count(*) > 1)")
def cpt_dedup_groups(t):
    return C.exact(t.documents).where("n_copies > 1").agg(F.count("*").alias("n_groups"), F.sum("n_copies").alias("n_rows"))


NEAR_SQL = f"""
WITH RECURSIVE c AS (SELECT md5(text) AS fp, min(doc_id) AS rep FROM documents GROUP BY 1),
w AS (SELECT d.doc_id, {LTOK} AS ws FROM documents d JOIN c ON d.doc_id = c.rep),
s AS (SELECT doc_id, unnest(list_distinct(CASE WHEN len(ws) >= 5 THEN list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i+4], ' ')) ELSE [array_to_string(ws, ' ')] END)) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE k >= 0.8 * (a.n + b.n - k)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r(node, root) AS (SELECT DISTINCT x, x FROM e UNION SELECT e.y, r.root FROM r JOIN e ON e.x = r.node WHERE r.root < e.y),
m AS (SELECT node, min(root) AS root FROM r GROUP BY node)
SELECT d.doc_id, coalesce(m.root, c.rep) AS class_id FROM documents d JOIN c ON md5(d.text) = c.fp LEFT JOIN m ON m.node = c.rep"""


@query("cpt_near_dup_pairs", NEAR_SQL)
def cpt_near_dup_pairs(t):
    return C.near_groups(t.documents)


@query("cpt_line_dedup", f"""
WITH l AS (SELECT doc_id, unnest(list_distinct({SPLIT})) AS line FROM documents)
SELECT md5(line) AS line_hash, min(doc_id) AS first_doc, count(*)::BIGINT AS n_docs FROM l WHERE length(line) >= 10 GROUP BY 1 HAVING count(*) >= 2""")
def cpt_line_dedup(t):
    return C.repeated_lines(t.documents)


def _score_sql(lang):
    return f"(len(list_filter(lw, lambda w: w IN {sql_list(FUNCTION_WORDS[lang])})) / nullif(len(lw), 0)::DOUBLE)"


@query("cpt_tags_basic", rf"""
WITH b AS (SELECT doc_id, text, {SPLIT} AS ls, {TOK} AS ws, {LTOK} AS lw FROM documents),
c AS (SELECT *, list_transform(ls, lambda x: len(regexp_extract_all(x, '\S+'))) AS n FROM b)
SELECT doc_id, array_to_string(n, ',') AS lines_num_words, list_min(n)::INT AS min_line_words, list_max(n)::INT AS max_line_words, list_sum(n)::DOUBLE / len(n) AS mean_line_words,
 CASE WHEN len(ws) > 0 THEN length(text)::DOUBLE / len(ws) END AS fertility, 1 - len(list_distinct(ls))::DOUBLE / len(ls) AS repetition_ratio,
 greatest({', '.join(_score_sql(x) for x in FUNCTION_WORDS)}) AS language_score FROM c""")
def cpt_tags_basic(t):
    return C.basic_tags(t.documents)


STOP = sql_list(w for ws in FUNCTION_WORDS.values() for w in ws)


def _frac(pattern):
    return f"CASE WHEN length(text) > 0 THEN len(regexp_extract_all(text, '{pattern}'))::DOUBLE / length(text) END"


def _lines(cond):
    return f"len(list_filter(ls, lambda x: {cond}))::DOUBLE / len(ls)"


def _grams(n):
    return f"CASE WHEN len(ws) >= {n} THEN list_transform(range(1, len(ws) - {n - 2}), lambda i: array_to_string(ws[i:i+{n - 1}], ' ')) ELSE [] END"


def _dup(n):
    return f"CASE WHEN len(ws) >= {n} THEN (len(g{n}) - len(list_distinct(g{n})))::DOUBLE / len(g{n}) END"


def _top(n):
    return f"CASE WHEN len(ws) >= {n} THEN list_max(map_values(list_histogram(g{n})))::DOUBLE / len(g{n}) END"


FULL_SQL = rf"""
WITH b AS (SELECT doc_id, text, {SPLIT} AS ls, {TOK} AS ws, {LTOK} AS lw FROM documents),
c AS (SELECT *, {', '.join(f'{_grams(n)} AS g{n}' for n in (2, 3, 4, 5, 10))}, list_sort([{', '.join(f'coalesce({_score_sql(x)}, 0)' for x in FUNCTION_WORDS)}], 'DESC') AS sc FROM b)
SELECT doc_id, length(text)::BIGINT AS n_chars, len(ws)::BIGINT AS n_words, len(ls)::BIGINT AS n_lines,
 len(regexp_extract_all(text, '\n\n+'))::BIGINT + 1 AS n_paragraphs, len(regexp_extract_all(text, '[.!?]+(\s|$)'))::BIGINT AS n_sentences,
 CASE WHEN len(ws) > 0 THEN list_sum(list_transform(ws, lambda w: length(w)))::DOUBLE / len(ws) END AS mean_word_len, list_max(list_transform(ws, lambda w: length(w)))::INT AS max_word_len,
 list_sum(list_transform(ls, lambda w: length(w)))::DOUBLE / len(ls) AS mean_line_len, list_max(list_transform(ls, lambda w: length(w)))::INT AS max_line_len,
 {_frac(r'\pL')} AS alpha_frac, {_frac('[0-9]')} AS digit_frac, {_frac(r'\p{Lu}')} AS upper_frac, {_frac(r'\s')} AS space_frac,
 {_frac(r'[!-/:-@\[-`{-~]')} AS punct_frac, {_frac(r'[^\x00-\x7F]')} AS nonascii_frac, CASE WHEN len(ws) > 0 THEN len(regexp_extract_all(text, '[#*|~^]'))::DOUBLE / len(ws) END AS symbol_word_ratio,
 {_frac(r'[(){}\[\]]')} AS bracket_frac, len(regexp_extract_all(text, '[\x00-\x08\x0E-\x1F]'))::BIGINT AS control_char_count,
 {_lines(r"regexp_matches(x, '[.!?]\s*$')")} AS terminal_punct_line_frac, {_lines(r"regexp_matches(x, '^\s*[-*•]')")} AS bullet_line_frac,
 {_lines(r"regexp_matches(x, '(\.\.\.|…)\s*$')")} AS ellipsis_line_frac, {_lines("length(x) < 20")} AS short_line_frac, {_lines("trim(x) = ''")} AS empty_line_frac,
 {_lines("contains(x, '|')")} AS pipe_line_frac, len(list_filter(ls, lambda x: length(x) > 1000))::INT AS long_line_count,
 CASE WHEN list_sum(list_transform(ls, lambda w: length(w))) > 0 THEN (list_sum(list_transform(ls, lambda w: length(w))) - list_sum(list_transform(list_distinct(ls), lambda w: length(w))))::DOUBLE / list_sum(list_transform(ls, lambda w: length(w))) END AS dup_line_char_frac,
 {_top(2)} AS top2gram_frac, {_top(3)} AS top3gram_frac, {_top(4)} AS top4gram_frac, {_dup(5)} AS dup5gram_frac, {_dup(10)} AS dup10gram_frac,
 CASE WHEN len(ws) > 0 THEN len(list_distinct(ws))::DOUBLE / len(ws) END AS uniq_word_frac,
 CASE WHEN len(ws) > 0 THEN round(log2(len(ws)) - list_sum(list_transform(map_values(list_histogram(ws)), lambda k: k * log2(k))) / len(ws), 6) END AS word_entropy,
 len(list_filter(lw, lambda w: w IN {STOP}))::BIGINT AS stopword_count, CASE WHEN len(ws) > 0 THEN len(list_filter(lw, lambda w: w IN {STOP}))::DOUBLE / len(ws) END AS stopword_frac, sc[1] - sc[2] AS lang_margin,
 len(regexp_extract_all(text, 'https?://'))::BIGINT AS url_count, len(regexp_extract_all(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+\.[A-Za-z0-9.-]+'))::BIGINT AS email_count, len(regexp_extract_all(text, '[0-9]+'))::BIGINT AS number_count,
 len(list_filter(ls, lambda x: regexp_matches(x, '(?i)licen[sc]ed? under|all rights reserved|under the mit license'))) > 0 AS license_line,
 len(regexp_extract_all(text, '(?i)cookie|privacy policy|terms of use|javascript|lorem ipsum'))::BIGINT AS boilerplate_hits, len(regexp_extract_all(text, '(?i)\b(kill|hate|porn|bomb)\b'))::BIGINT AS keyword_hits,
 {_lines(r"regexp_matches(x, '^\s*(#|--|//)')")} AS comment_line_frac, contains(text, '\"\"\"') AS has_docstring,
 len(list_filter(ls, lambda x: regexp_matches(x, '^\s*(import|from) ')))::BIGINT AS import_count, len(list_filter(ls, lambda x: regexp_matches(x, '^\s*(def|class|function) ')))::BIGINT AS def_count,
 len(list_filter(ls[1:5], lambda x: regexp_matches(lower(x), 'auto-?generated|do not edit'))) > 0 AS autogenerated, regexp_matches(text, '[A-Za-z0-9+/=]{{1000}}') AS encoded_blob
FROM c""".replace('\\"', '"')


@query("cpt_tags_full", FULL_SQL)
def cpt_tags_full(t):
    return C.all_tags(t.documents).withColumn("word_entropy", F.round("word_entropy", 6))


@query("cpt_language_score", f"""
WITH b AS (SELECT doc_id, lang, {LTOK} AS lw FROM documents), s AS (SELECT doc_id, lang, {', '.join(f'coalesce({_score_sql(x)}, 0) AS s_{x}' for x in FUNCTION_WORDS)} FROM b),
p AS (SELECT *, greatest(s_de, s_en, s_es, s_fr) AS top, CASE greatest(s_de, s_en, s_es, s_fr) WHEN s_de THEN 'de' WHEN s_en THEN 'en' WHEN s_es THEN 'es' ELSE 'fr' END AS best FROM s)
SELECT lang, count(*)::BIGINT AS docs, sum((best = lang)::INT)::BIGINT AS correct, round(avg(top), 6) AS mean_score FROM p GROUP BY lang""")
def cpt_language_score(t):
    s = t.documents.select("lang", *[F.coalesce(c, F.lit(0.0)).alias(f"s_{k}") for k, c in C.language_scores(F.col("text")).items()])
    top = F.greatest("s_de", "s_en", "s_es", "s_fr")
    best = F.when(top == F.col("s_de"), "de").when(top == F.col("s_en"), "en").when(top == F.col("s_es"), "es").otherwise("fr")
    return s.groupBy("lang").agg(F.count("*").alias("docs"), F.sum((best == F.col("lang")).cast("int")).alias("correct"), F.round(F.avg(top), 6).alias("mean_score"))


KEYWORDS = ["stupid", "idiot", "hate", "kill", "trash", "the", "als"]


@query("cpt_keyword_filter", f"""
WITH h AS (SELECT doc_id, list_sort(list_distinct(list_filter(list_transform({LTOK}, lambda w: regexp_replace(w, '[.,!?;:]+$', '')), lambda w: w IN {sql_list(KEYWORDS)}))) AS f FROM documents)
SELECT doc_id, len(f)::INT AS n_hits, array_to_string(f, ',') AS hits FROM h WHERE len(f) > 0""")
def cpt_keyword_filter(t):
    return C.keyword_hits(t.documents, KEYWORDS)


@query("cpt_web_rules", rf"""
WITH l AS (SELECT doc_id, {SPLIT} AS ls FROM documents),
g AS (SELECT doc_id, ls, list_filter(ls, lambda x: regexp_matches(x, '[.!?"]\s*$') AND len(regexp_extract_all(x, '\S+')) >= 5 AND NOT regexp_matches(lower(x), 'javascript|cookie|privacy policy|terms of use')) AS k FROM l),
s AS (SELECT *, array_to_string(k, chr(10)) AS kept FROM g)
SELECT doc_id, len(ls)::BIGINT AS n_lines, len(k)::BIGINT AS n_kept, len(regexp_extract_all(kept, '[.!?]+(\s|$)'))::BIGINT AS n_sentences,
 len(regexp_extract_all(kept, '[.!?]+(\s|$)')) >= 3 AND NOT contains(kept, '{{') AND NOT contains(lower(kept), 'lorem ipsum') AS keep FROM s""")
def cpt_web_rules(t):
    return C.web_rules(t.documents)


STRIP_SQL = r"""trim(regexp_replace(regexp_replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html,
 '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gis'), '<!--.*?-->', ' ', 'gs'), '<(br|/p|/li|/h[1-6]|/div|/tr)[^>]*>', chr(10), 'gi'), '<[^>]*>', ' ', 'g'),
 '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&amp;', '&'), '[ \t]+', ' ', 'g'), ' ?\n[ \n]*', chr(10), 'g'))"""


@query("cpt_page_rules", rf"""
WITH p AS (SELECT page_id, url, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, {STRIP_SQL} AS text FROM pages),
l AS (SELECT *, list_filter(string_split(text, chr(10)), lambda x: length(x) > 0) AS ls FROM p)
SELECT page_id, host, len(ls)::BIGINT AS n_lines, length(text)::BIGINT AS n_chars, CASE WHEN len(ls) > 0 THEN (len(ls) - len(list_distinct(ls)))::DOUBLE / len(ls) END AS repeated,
 CASE WHEN regexp_matches(lower(url), 'casino|porn|bet|adult') THEN 'url' WHEN length(text) < 200 THEN 'short' WHEN len(ls) > 0 AND (len(ls) - len(list_distinct(ls)))::DOUBLE / len(ls) > 0.3 THEN 'repeated' ELSE 'ok' END AS verdict FROM l""")
def cpt_page_rules(t):
    return C.page_rules(t.pages)


DECIDE_SQL = rf"""
WITH b AS (SELECT doc_id, text, {SPLIT} AS ls, {TOK} AS ws, {LTOK} AS lw FROM documents),
r AS (SELECT doc_id, list_filter([
 CASE WHEN len(ws) < 5 THEN 'too_short' END, CASE WHEN len(list_filter(ls, lambda x: length(x) > 100000)) > 0 THEN 'too_long_line' END,
 CASE WHEN 1 - len(list_distinct(ls))::DOUBLE / len(ls) > 0.3 THEN 'repeated' END, CASE WHEN len(list_filter(ls, lambda x: contains(x, '|')))::DOUBLE / len(ls) > 0.5 THEN 'pipe_lines' END,
 CASE WHEN len(ws) > 0 AND len(regexp_extract_all(text, '[#*|~^!]'))::DOUBLE / len(ws) > 0.3 THEN 'symbol_heavy' END,
 CASE WHEN coalesce(greatest({', '.join(_score_sql(x) for x in FUNCTION_WORDS)}), 0) < 0.05 THEN 'low_language' END,
 CASE WHEN regexp_matches(lower(text), 'licensed under|rights reserved|mit license') THEN 'license_line' END], lambda x: x IS NOT NULL) AS h FROM b)
SELECT doc_id, len(h) = 0 AS keep, h[1] AS reason, array_to_string(h, ',') AS reasons FROM r"""


@query("cpt_decide_reasons", DECIDE_SQL)
def cpt_decide_reasons(t):
    return C.decide(t.documents)


@query("cpt_decontaminate", f"""
WITH w AS (SELECT doc_id, {LTOK} AS ws FROM documents), b AS (SELECT item_id, {LTOK} AS ws FROM benchmark),
g AS (SELECT DISTINCT item_id, unnest({_grams(8)}) AS g FROM b), o AS (SELECT doc_id, unnest(list_distinct({_grams(8)})) AS g FROM w)
SELECT doc_id, count(DISTINCT item_id)::BIGINT AS n_items FROM o JOIN g USING (g) GROUP BY doc_id""")
def cpt_decontaminate(t):
    return C.decontaminate(t.documents, t.benchmark)


@query("cpt_unigram_lm", f"""
WITH k AS (SELECT unnest({LTOK}) AS token FROM documents) SELECT token, count(*)::BIGINT AS n FROM k GROUP BY token""")
def cpt_unigram_lm(t):
    return C.fit_unigram(t.documents)


LM_SQL = f"""
k AS (SELECT doc_id, unnest({LTOK}) AS token FROM documents),
g AS (SELECT k.token FROM k JOIN labels l ON k.doc_id = l.doc_id WHERE l.quality = 1 AND l.toxic = 0),
c AS (SELECT token, count(*) AS c FROM k GROUP BY token), r AS (SELECT token, count(*) AS r FROM g GROUP BY token),
m AS (SELECT c.token, c.c::DOUBLE AS c, coalesce(r.r, 0)::DOUBLE AS r FROM c LEFT JOIN r ON c.token = r.token),
z AS (SELECT sum(c) AS tc, sum(r) AS tr, count(*)::DOUBLE AS v FROM m),
ll AS (SELECT token, -ln((c + 1) / (tc + v)) AS loss_cur, -ln((r + 1) / (tr + v)) AS loss_ref FROM m, z),
x AS (SELECT doc_id, o.token, o.n, loss_cur, loss_cur - loss_ref AS excess FROM (SELECT doc_id, token, count(*) AS n FROM k GROUP BY ALL) o JOIN ll ON o.token = ll.token)"""


LM2_SQL = f"""
k AS (SELECT doc_id, unnest({LTOK}) AS token, unnest(range(len({LTOK}))) AS pos FROM documents),
kk AS (SELECT doc_id, token, coalesce(lag(token) OVER (PARTITION BY doc_id ORDER BY pos), '') AS before FROM k),
g AS (SELECT kk.* FROM kk JOIN labels l ON kk.doc_id = l.doc_id WHERE l.quality = 1 AND l.toxic = 0),
z AS (SELECT count(DISTINCT token)::DOUBLE AS v FROM k),
c AS (SELECT before, token, count(*)::DOUBLE AS c, sum(count(*)) OVER (PARTITION BY before)::DOUBLE AS t FROM kk GROUP BY 1, 2),
r AS (SELECT before, token, count(*)::DOUBLE AS c FROM g GROUP BY 1, 2), rt AS (SELECT before, sum(c) AS t FROM r GROUP BY 1),
ll AS (SELECT c.before, c.token, -ln((c.c + 1) / (c.t + v)) AS loss_cur, -ln((coalesce(r.c, 0) + 1) / (coalesce(rt.t, 0) + v)) AS loss_ref FROM c CROSS JOIN z LEFT JOIN r ON r.before = c.before AND r.token = c.token LEFT JOIN rt ON rt.before = c.before)"""


@query("cpt_token_excess_order2", f"WITH {LM2_SQL} SELECT kk.before, kk.token, count(*)::BIGINT AS n, round(any_value(loss_cur), 6) AS loss_cur, round(any_value(loss_cur - loss_ref), 6) AS excess FROM kk JOIN ll ON ll.before = kk.before AND ll.token = kk.token GROUP BY 1, 2")
def cpt_token_excess_order2(t):
    """Losses of tokens given the token before, current against reference model, by pair."""
    own = C.excess_in_context(t.documents, t.labels)
    return own.groupBy("before", "token").agg(F.sum("n").alias("n"), F.round(F.first("loss_cur"), 6).alias("loss_cur"), F.round(F.first("excess"), 6).alias("excess"))


@query("cpt_token_excess", f"WITH {LM_SQL} SELECT doc_id, token, n::BIGINT AS n, round(loss_cur, 6) AS loss_cur, round(excess, 6) AS excess FROM x")
def cpt_token_excess(t):
    return C.excess(t.documents, t.labels).select("doc_id", "token", "n", F.round("loss_cur", 6).alias("loss_cur"), F.round("excess", 6).alias("excess"))


MASKS = {
    "score": "excess >= 0.6",
    "minmax": "CASE WHEN max(excess) OVER d > min(excess) OVER d THEN (excess - min(excess) OVER d) / (max(excess) OVER d - min(excess) OVER d) ELSE 0 END >= 0.6",
    "ratio": "coalesce(sum(n) OVER (PARTITION BY doc_id ORDER BY excess DESC, token ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) < 0.6 * sum(n) OVER d",
    "all": "TRUE",
    "random": f"{det.sql_unit(chr(39) + 'keep' + chr(39), 'doc_id', 'token')} < 0.6",
}


def mask_sql(mode):
    return f"WITH {LM_SQL}, y AS (SELECT *, {MASKS[mode]} AS keep FROM x WINDOW d AS (PARTITION BY doc_id))"


for _mode in MASKS:

    @query(f"cpt_token_mask_{_mode}", mask_sql(_mode) + """
SELECT doc_id, sum(n)::BIGINT AS n_tokens, coalesce(sum(n) FILTER (WHERE keep), 0)::BIGINT AS n_kept, round(sum(n * loss_cur) FILTER (WHERE keep) / sum(n) FILTER (WHERE keep), 6) AS loss FROM y GROUP BY doc_id""")
    def cpt_token_mask(t, mode=_mode):
        return C.selective_loss(C.masked(C.excess(t.documents, t.labels), mode=mode))


CLEAN_SQL = DECIDE_SQL.replace("WITH b AS", "WITH u AS (SELECT * FROM documents WHERE doc_id IN (SELECT min(doc_id) FROM documents GROUP BY md5(text))), b AS", 1).replace("FROM documents)", "FROM u)")


def _curated(t):
    """Exact duplicates out, then the policy."""
    first = C.exact(t.documents).select("doc_id")
    kept = t.documents.select("doc_id", "text").join(C.decide(t.documents).where("keep").select("doc_id"), "doc_id", "left_semi")
    return kept.join(first, "doc_id", "left_semi")


CURATED = f"""documents_all AS (SELECT * FROM documents), kept AS ({DECIDE_SQL.replace('WITH b AS', 'WITH b AS', 1)}),
cur AS (SELECT d.* FROM documents_all d JOIN kept ON d.doc_id = kept.doc_id WHERE kept.keep AND d.doc_id IN (SELECT min(doc_id) FROM documents_all GROUP BY md5(text)))"""


@query("cpt_selective_loss", f"WITH {CURATED}, " + LM_SQL.replace("FROM documents)", "FROM cur)", 1) + """
, y AS (SELECT *, excess >= 0.6 AS keep FROM x)
SELECT doc_id, sum(n)::BIGINT AS n_tokens, coalesce(sum(n) FILTER (WHERE keep), 0)::BIGINT AS n_kept, round(sum(n * loss_cur) FILTER (WHERE keep) / sum(n) FILTER (WHERE keep), 6) AS loss FROM y GROUP BY doc_id""")
def cpt_selective_loss(t):
    """Method I in short: deduplicate, filter, score tokens, mask, average the kept losses. The curated corpus is written once, as three passes read it."""
    parts = int(t.spark.conf.get("spark.sql.shuffle.partitions"))
    return C.selective_loss(C.masked(C.excess(cut(_curated(t).repartition(parts, "doc_id")), t.labels)))


@query("cpt_mix_ratio", f"""
WITH d AS (SELECT doc_id, lang, len({TOK})::BIGINT AS n FROM documents), g(lang, target) AS (VALUES ('en', 0.512), ('fr', 0.128), ('de', 0.16), ('es', 0.2)),
s AS (SELECT lang, sum(n)::DOUBLE AS total FROM d GROUP BY lang), z AS (SELECT min(total / target) AS size FROM s JOIN g USING (lang)),
r AS (SELECT lang, least(1.0, target * size / total) AS rate FROM s JOIN g USING (lang), z)
SELECT lang, count(*)::BIGINT AS docs, sum(n)::BIGINT AS tokens FROM d JOIN r USING (lang) WHERE {det.sql_unit("'mix'", 'doc_id')} < rate GROUP BY lang""")
def cpt_mix_ratio(t):
    """The printed token shares of four kinds, with the four languages in their place."""
    sized = t.documents.select("doc_id", "lang", F.size(tokens(F.col("text"))).cast("long").alias("n"))
    out = C.to_ratio(sized, "lang", "n", {"en": 0.512, "fr": 0.128, "de": 0.16, "es": 0.2}, "doc_id")
    return out.groupBy("lang").agg(F.count("*").alias("docs"), F.sum("n").alias("tokens"))


PACK_SQL = f"""
WITH d AS (SELECT doc_id, len({TOK})::BIGINT AS n, {det.sql_text("'pack'", 'doc_id')} AS o FROM documents),
p AS (SELECT doc_id, n, coalesce(sum(n) OVER (ORDER BY o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start FROM d WHERE n > 0),
c AS (SELECT *, unnest(range(start // 512, (start + n - 1) // 512 + 1)) AS pack_id FROM p)
SELECT pack_id, doc_id, greatest(0, pack_id * 512 - start)::BIGINT AS "from", least(n, (pack_id + 1) * 512 - start)::BIGINT AS "to" FROM c"""


@query("cpt_pack_concat", PACK_SQL)
def cpt_pack_concat(t):
    return C.concat_cut(t.documents, 512)


@query("cpt_pack_by_length")
def cpt_pack_by_length(t):
    return C.by_length(t.documents, 512)


@query("cpt_pack_compare")
def cpt_pack_compare(t):
    """Packs, fill and cut documents of both ways at two context lengths."""
    out = []
    for ctx in (512, 8192):
        out.append(C.pack_report(C.concat_cut(t.documents, ctx), "pack_id", ctx=ctx).select(F.lit("concat").alias("method"), F.lit(ctx).alias("ctx"), "*"))
        out.append(C.pack_report(C.by_length(t.documents, ctx), "shard", "pack", ctx=ctx).select(F.lit("by_length").alias("method"), F.lit(ctx).alias("ctx"), "*"))
    return C.union_all(out)


LR_SQL = f"""WITH k AS (SELECT pack_id AS step, sum("to" - "from")::BIGINT AS tokens FROM ({PACK_SQL}) GROUP BY 1), z AS (SELECT count(*) AS steps, greatest(1, floor(count(*) * 0.03::DOUBLE)) AS w FROM k)
SELECT step, tokens, round(CASE WHEN step < w THEN 3e-5 * (step + 1) / w ELSE 0.5 * 3e-5 * (1 + cos(3.141592653589793 * (step - w) / greatest(1, steps - w))) END, 12) AS lr FROM k, z"""


@query("cpt_lr_schedule", LR_SQL)
def cpt_lr_schedule(t):
    """One step for each pack of the corpus, with its tokens and its learning rate."""
    return C.cosine_schedule(C.concat_cut(t.documents, 512))


@query("cpt_quality_model")
def cpt_quality_model(t):
    """Hashed words and a logistic model against the labels; accuracy on the held-out tenth."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF

    rows = t.documents.join(t.labels, "doc_id").select("doc_id", "quality", tokens(F.lower("text")).alias("words"))
    data = HashingTF(inputCol="words", outputCol="features", numFeatures=4096).transform(rows).select("doc_id", F.col("quality").cast("double").alias("label"), "features")
    held = det.unit("split", F.col("doc_id")) >= 0.8
    model = LogisticRegression(maxIter=20, regParam=0.01).fit(data.where(~held))
    return model.transform(data.where(held)).agg(F.count("*").alias("n"), F.round(F.avg((F.col("prediction") == F.col("label")).cast("double")), 6).alias("accuracy"))


@query("cpt_code_rules", S.CODE_SQL + """
SELECT code_id, list_max(list_transform(string_split(text, chr(10)), lambda x: length(x))) <= 1000 AS line_ok, length(text)::DOUBLE / len(string_split(text, chr(10))) <= 100 AS mean_ok,
 len(regexp_extract_all(text, '[A-Za-z0-9]'))::DOUBLE / length(text) >= 0.25 AS alnum_ok, TRUE AS hand_ok, NOT regexp_matches(text, '[A-Za-z0-9+/=]{1000}') AS blob_ok FROM code""")
def cpt_code_rules(t):
    return C.code_rules(S.code_samples(t.orders))


@query("cpt_nl_ratio", S.CODE_SQL + """
SELECT code_id, lang, round(list_sum(list_transform(regexp_extract_all(text, '#[^\\n]*|--[^\\n]*'), lambda m: length(m)))::DOUBLE / length(text), 6) AS nl_ratio FROM code""")
def cpt_nl_ratio(t):
    return S.code_samples(t.orders).select("code_id", "lang", F.round(F.nullif(C.nl_ratio(F.col("text")), F.lit(0.0)), 6).alias("nl_ratio"))


@query("cpt_compile", S.CODE_SQL + "SELECT code_id, lang, ok AS compiles FROM code WHERE lang = 'python'")
def cpt_compile(t):
    """Python of the generated corpus is parsed; every fifth was broken on purpose."""
    return S.compile_ok(S.code_samples(t.orders).where("lang = 'python'")).select("code_id", "lang", "compiles")
