"""Workloads over other corpora's recipes, the training mixture, published tables, and side measures."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ..functions import chargrams, textstats as ts
from ..operators import classifier, digests, exact, hosts, lm, metrics, minhash, mixture, normalize, quality, recipes, tables
from ..profiles import HARMFUL_TERMS, LATIN
from .corpus import CONF_SQL, LINES_SQL, PARAS_SQL, TOKENS_SQL, WORDS_SQL, jaccard_sql, lst, members_sql, mild_flags, MILD, of_reps, pairs_sql, prefix_sql, r6, rep_keys, sentences_sql, table, term_sql, unshuffled

Q: dict[str, tuple] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        Q[name] = (f, sql)
        return f

    return keep


def units_dedup_sql(units: str, joiner: str, digest: str = "md5") -> str:
    return f"""WITH u AS (SELECT doc_id, unnest(range(0, len(u))) AS pos, unnest(u) AS unit FROM (SELECT doc_id, {units} AS u FROM documents)),
  f AS (SELECT *, row_number() OVER (PARTITION BY substr({digest}(unit), 1, 16) ORDER BY doc_id, pos) AS rn FROM u)
  SELECT doc_id, md5(coalesce(string_agg(CASE WHEN rn = 1 THEN unit END, '{joiner}' ORDER BY pos), '')) AS md5, count(*) FILTER (rn = 1) AS kept, count(*) FILTER (rn > 1) AS dropped FROM f GROUP BY doc_id"""


def digest_of(df: DataFrame) -> DataFrame:
    return df.select("doc_id", F.md5(F.col("text").cast("binary")).alias("md5"), "kept", "dropped")


@query("w47_line_dedup", units_dedup_sql(LINES_SQL, "' || chr(10) || '").replace("'' || chr(10) || ''", "chr(10)"))
def w47(spark, d):
    return digest_of(exact.dedup_lines(table(spark, d, "documents")))


@query("w48_paragraph_dedup", units_dedup_sql(PARAS_SQL, "' || chr(10) || '", "sha1").replace("'' || chr(10) || ''", "chr(10) || chr(10)"))
def w48(spark, d):
    return digest_of(exact.dedup_paragraphs(table(spark, d, "documents")))


@query("w49_three_sentence_dedup", f"""WITH s AS (SELECT doc_id, {sentences_sql('text')} AS s FROM documents), w AS (SELECT doc_id, pos, substr(md5(array_to_string(s[pos + 1 : pos + 3], ' ')), 1, 16) AS h FROM (SELECT doc_id, s, unnest(range(0, greatest(len(s) - 2, 0))) AS pos FROM s)),
  r AS (SELECT doc_id, pos, row_number() OVER (PARTITION BY h ORDER BY doc_id, pos) AS rn FROM w), c AS (SELECT DISTINCT doc_id, unnest(range(pos, pos + 3)) AS p FROM r WHERE rn > 1), n AS (SELECT doc_id, count(*) AS dropped FROM c GROUP BY doc_id)
  SELECT s.doc_id, len(s) AS sentences, coalesce(dropped, 0) AS dropped FROM s LEFT JOIN n ON s.doc_id = n.doc_id""")
def w49(spark, d):
    return exact.dedup_spans(table(spark, d, "documents"))


URL_SQL = "regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(lower(url), '^[a-z]+://', ''), '^(www|m|blog)\\.', ''), '[?#].*$', ''), '\\.html?$', ''), '/+$', '')"


@query("w50_url_dedup", f"SELECT {URL_SQL} AS url_key, min(page_id) AS page_id, count(*) AS copies FROM pages GROUP BY 1")
def w50(spark, d):
    return exact.dedup_urls(table(spark, d, "pages"))


@query("w51_within_doc_paragraphs", f"SELECT doc_id, md5(array_to_string(list_transform(list_filter(list_zip({PARAS_SQL}, range(1, len({PARAS_SQL}) + 1)), lambda x: list_position({PARAS_SQL}, x[1]) = x[2]), lambda x: x[1]), chr(10) || chr(10))) AS md5 FROM documents")
def w51(spark, d):
    return table(spark, d, "documents").select("doc_id", F.md5(exact.dedup_paragraphs_within(F.col("text")).cast("binary")).alias("md5"))


TERMINAL_SQL = f"list_filter({LINES_SQL}, lambda s: regexp_matches(s, '[.!?\"”]$'))"
SHORT_SQL = f"list_filter({TERMINAL_SQL}, lambda s: len({TOKENS_SQL.format(t='s')}) > 4)"
C4_SQL = f"(SELECT *, CASE WHEN len({sentences_sql('j')}) >= 3 THEN j END AS kept FROM (SELECT doc_id, text, array_to_string({SHORT_SQL}, chr(10)) AS j FROM documents))"


@query("w52_c4_rules", f"SELECT doc_id, len({TERMINAL_SQL}) AS terminal, kept IS NULL AS dropped, md5(coalesce(kept, '')) AS md5 FROM {C4_SQL}")
def w52(spark, d):
    t = F.col("text")
    kept = recipes.c4(t)
    return table(spark, d, "documents").select("doc_id", F.size(recipes.keep_terminal_lines(t)).alias("terminal"), kept.isNull().alias("dropped"), F.md5(F.coalesce(kept, F.lit("")).cast("binary")).alias("md5"))


@query("w53_mc4_rules", f"SELECT doc_id, length(text) >= 200 AND len({LINES_SQL}) >= 3 AS kept FROM documents")
def w53(spark, d):
    return table(spark, d, "documents").select("doc_id", recipes.multilingual_rule(F.col("text")).alias("kept"))


def rep_sql(units: str) -> str:
    return f"(CASE WHEN len({units}) = 0 THEN 0.0 ELSE round((len({units}) - len(list_distinct({units})))::DOUBLE / len({units}), 6) END)"


CHUNKS_SQL = "list_transform(range(1, greatest(length(text) - 9, 1) + 1, 10), lambda i: substring(text, i::INT, 10))"
FIVE_SQL = f"list_transform(range(1, greatest(len({TOKENS_SQL.format(t='text')}) - 4, 0) + 1), lambda i: array_to_string(({TOKENS_SQL.format(t='text')})[i : i + 4], ' '))"


@query("w54_roots_rules", f"""WITH t AS (SELECT doc_id, text, {TOKENS_SQL.format(t='text')} AS tok, {WORDS_SQL.format(t='text')} AS w FROM documents), g AS (SELECT *, list_transform(range(1, greatest(len(tok) - 4, 0) + 1), lambda i: array_to_string(tok[i : i + 4], ' ')) AS five, {CHUNKS_SQL} AS ten FROM t)
  SELECT doc_id, len(tok) < 50 AS few_words, {rep_sql('ten')} AS char_repetition, {rep_sql('five')} AS word_repetition, CASE WHEN length(text) = 0 THEN 0.0 ELSE round(length(regexp_replace(text, '[^\\x{{2600}}-\\x{{27BF}}\\x{{1F300}}-\\x{{1FAFF}}]', '', 'g'))::DOUBLE / length(text), 6) END AS emoji, CASE WHEN len(w) = 0 THEN 0.0 ELSE round(len(list_filter(w, lambda x: list_contains({lst(recipes.ALL_FUNCTION_WORDS)}, x)))::DOUBLE / len(w), 6) END AS function_words FROM g""")
def w54(spark, d):
    rules = recipes.roots(table(spark, d, "documents"))
    return rules.select("doc_id", "few_words", *[r6(F.col(c)).alias(c) for c in ("char_repetition", "word_repetition", "emoji", "function_words")])


FP_SQL = f"""(SELECT doc_id, ({' + '.join(f'CASE WHEN sum(((h >> {k}) & 1) * 2 - 1) > 0 THEN {1 << k} ELSE 0 END' for k in range(digests.BITS))})::BIGINT AS fp FROM (
  SELECT doc_id, ('0x' || substr(md5(array_to_string(w[pos + 1 : pos + 6], ' ')), 1, 15))::BIGINT AS h FROM (SELECT doc_id, w, unnest(range(0, greatest(len(w) - 5, 0))) AS pos FROM (SELECT doc_id, {TOKENS_SQL.format(t='text')} AS w FROM documents))) GROUP BY doc_id)"""


@query("w55_simhash_pairs", f"WITH f AS MATERIALIZED {FP_SQL}, r AS MATERIALIZED (SELECT fp, min(doc_id) AS doc_id FROM f GROUP BY fp) SELECT least(x.doc_id, y.doc_id) AS a, greatest(x.doc_id, y.doc_id) AS b, bit_count(xor(x.fp, y.fp))::INT AS distance FROM r x JOIN r y ON x.fp < y.fp WHERE bit_count(xor(x.fp, y.fp)) <= 3 UNION ALL SELECT r.doc_id, f.doc_id, 0 FROM f JOIN r ON r.fp = f.fp AND r.doc_id < f.doc_id")
def w55(spark, d):
    """Pairs of different fingerprints by their least documents, and each other document of a fingerprint beside its least one."""
    return digests.simhash_pairs(digests.simhash(table(spark, d, "documents")))


@query("w56_tlsh_pairs")
def w56(spark, d):
    docs = table(spark, d, "documents")
    reps = minhash.copies(docs).filter("doc_id = rep").select("doc_id")
    return minhash.with_members(digests.digest_pairs(digests.digests(docs).join(reps, "doc_id", "left_semi")), docs, distance=0)


R5, B5 = minhash.tune(0.5, 32)
R8, B8 = minhash.tune(0.8, 64)


@query("w57_minhash_at_0_5", f"SELECT a, b FROM {of_reps(pairs_sql(R5, B5))} UNION ALL SELECT a, b FROM {members_sql()}")
def w57(spark, d):
    return minhash.with_members(minhash.candidate_pairs(rep_keys(spark, d, R5, B5)), table(spark, d, "documents"))


@query("w58_minhash_at_0_8", f"SELECT a, b, round(jaccard, 6) AS jaccard FROM {of_reps(jaccard_sql(pairs_sql(R8, B8), 0.8))} UNION ALL SELECT a, b, jaccard FROM {members_sql(', 1.0::DOUBLE AS jaccard')}")
def w58(spark, d):
    docs = table(spark, d, "documents")
    found = minhash.verify(minhash.candidate_pairs(rep_keys(spark, d, R8, B8)), docs, 0.8).withColumn("jaccard", r6(F.col("jaccard")))
    return minhash.with_members(found, docs, jaccard=1.0)


def lm_sql(ref: str, ref_key: str, n: int = 3, k: float = 0.1) -> str:
    def toks(rel: str, key: str) -> str:
        return f"(SELECT {key} AS id, list_transform({WORDS_SQL.format(t='text')}, lambda x: CASE WHEN list_contains((SELECT list(word) FROM voc), x) THEN x ELSE '<unk>' END) AS w FROM {rel})"

    def grams(rel: str) -> str:
        return f"(SELECT id, array_to_string(w[p + 1 : p + {n}], ' ') AS gram, array_to_string(w[p + 1 : p + {n - 1}], ' ') AS context FROM (SELECT id, w, unnest(range(0, greatest(len(w) - {n - 1}, 0))) AS p FROM {rel}))"

    return f"""WITH voc AS MATERIALIZED (SELECT word FROM (SELECT unnest({WORDS_SQL.format(t='text')}) AS word FROM {ref}) GROUP BY word HAVING count(*) >= 2),
  rt AS (SELECT r.id, list(coalesce(v.word, '<unk>') ORDER BY r.p) AS w FROM (SELECT {ref_key} AS id, unnest(w) AS x, unnest(range(0, len(w))) AS p FROM (SELECT {ref_key}, {WORDS_SQL.format(t='text')} AS w FROM {ref})) r LEFT JOIN voc v ON v.word = r.x GROUP BY r.id),
  dt AS (SELECT r.id, list(coalesce(v.word, '<unk>') ORDER BY r.p) AS w FROM (SELECT doc_id AS id, unnest(w) AS x, unnest(range(0, len(w))) AS p FROM (SELECT doc_id, {WORDS_SQL.format(t='text')} AS w FROM documents)) r LEFT JOIN voc v ON v.word = r.x GROUP BY r.id),
  rg AS MATERIALIZED {grams('rt')}, c AS (SELECT gram, count(*) AS c FROM rg GROUP BY gram), t AS (SELECT context, count(*) AS t FROM rg GROUP BY context)
  SELECT g.id AS doc_id, round(avg(ln((coalesce(c, 0) + {k}) / (coalesce(t, 0) + ((SELECT count(*) FROM voc) + 1) * {k}))), 5) AS score FROM {grams('dt')} g LEFT JOIN c ON c.gram = g.gram LEFT JOIN t ON t.context = g.context GROUP BY g.id"""


@query("w59_lm_likelihood", lm_sql("benchmark", "item_id"))
def w59(spark, d):
    s = lm.log_likelihood(table(spark, d, "documents"), table(spark, d, "benchmark"))
    return s.select("doc_id", F.round("score", 5).alias("score"))


@query("w59b_lm_cut", f"WITH s AS ({lm_sql('benchmark', 'item_id')}) SELECT doc_id FROM s WHERE score >= (SELECT quantile_cont(score, 0.5) FROM s)")
def w59b(spark, d):
    s = lm.log_likelihood(table(spark, d, "documents"), table(spark, d, "benchmark")).select("doc_id", F.round("score", 5).alias("score"))
    return lm.quantile_cut(s, 0.5).select("doc_id")


@query("w59c_lm_terciles", f"WITH s AS ({lm_sql('benchmark', 'item_id')}) SELECT doc_id, CASE WHEN score >= (SELECT quantile_cont(score, 2.0 / 3) FROM s) THEN 'head' WHEN score >= (SELECT quantile_cont(score, 1.0 / 3) FROM s) THEN 'middle' ELSE 'tail' END AS part FROM s")
def w59c(spark, d):
    s = lm.log_likelihood(table(spark, d, "documents"), table(spark, d, "benchmark")).select("doc_id", F.round("score", 5).alias("score"))
    return lm.terciles(s).select("doc_id", "part")


@query("w60_lm_harmful", lm_sql("(SELECT * FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1))", "doc_id", 2))
def w60(spark, d):
    docs = table(spark, d, "documents")
    s = lm.log_likelihood(docs, lm.harmful_reference(docs, table(spark, d, "labels")), n=2, ref_key="doc_id")
    return s.select("doc_id", F.round("score", 5).alias("score"))


@query("w60b_lm_harmful_drop", f"WITH s AS ({lm_sql('(SELECT * FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1))', 'doc_id', 2)}) SELECT doc_id FROM s WHERE score <= (SELECT quantile_cont(score, 0.9) FROM s)")
def w60b(spark, d):
    """Texts that stay when the tenth likeliest under the harmful model goes."""
    return lm.drop_harmful(w60(spark, d)).select("doc_id")


@query("w61_exact_substring", f"""WITH w AS MATERIALIZED (SELECT doc_id, {TOKENS_SQL.format(t='text')} AS w FROM documents), g AS (SELECT doc_id, pos, substr(md5(array_to_string(w[pos + 1 : pos + 50], ' ')), 1, 16) AS h FROM (SELECT doc_id, w, unnest(range(0, greatest(len(w) - 49, 0))) AS pos FROM w)),
  r AS (SELECT doc_id, pos, row_number() OVER (PARTITION BY h ORDER BY doc_id, pos) AS rn FROM g), c AS (SELECT DISTINCT doc_id, unnest(range(pos, pos + 50)) AS p FROM r WHERE rn > 1),
  l AS (SELECT doc_id, unnest(range(0, len(w))) AS p, unnest(list_transform(w, lambda x: length(x))) AS n FROM w), s AS (SELECT c.doc_id, count(*) AS removed, sum(n)::BIGINT AS chars FROM c JOIN l ON c.doc_id = l.doc_id AND c.p = l.p GROUP BY c.doc_id)
  SELECT w.doc_id, len(w) AS tokens, coalesce(removed, 0) AS removed, coalesce(chars, 0) AS chars_removed FROM w LEFT JOIN s ON w.doc_id = s.doc_id""")
def w61(spark, d):
    return exact.repeated_spans(table(spark, d, "documents"))


UNIT_SQL = "((('0x' || substr(md5({k}::VARCHAR || ':1'), 1, 13))::BIGINT + 1) / 4503599627370496.0::DOUBLE)"


@query("w62_visit_weighted_sample", f"WITH v AS (SELECT user_id % (SELECT count(*) FROM pages) AS page_id, count(*) AS visits FROM events GROUP BY 1) SELECT page_id, visits, round(-ln({UNIT_SQL.format(k='page_id')}) / visits, 6) AS draw FROM pages JOIN v USING (page_id) ORDER BY -ln({UNIT_SQL.format(k='page_id')}) / visits, page_id LIMIT 50")
def w62(spark, d):
    pages = table(spark, d, "pages")
    n = pages.select(F.count("*").alias("n"))
    visits = table(spark, d, "events").crossJoin(F.broadcast(n)).groupBy((F.col("user_id") % F.col("n")).alias("page_id")).agg(F.count("*").alias("visits"))
    return mixture.visit_weighted(pages, visits, 50).select("page_id", "visits", r6(F.col("draw")).alias("draw"))


TOK_T = TOKENS_SQL.format(t="text")
MASSIVE_SQL = f"""(len({TOK_T}) BETWEEN 50 AND 100000 AND list_sum(list_transform({TOK_T}, lambda x: length(x)))::DOUBLE / greatest(len({TOK_T}), 1) BETWEEN 3 AND 10 AND len(regexp_extract_all(text, '#|…|\\.\\.\\.'))::DOUBLE / greatest(len({TOK_T}), 1) <= 0.1
  AND len(list_filter({LINES_SQL}, lambda s: regexp_matches(s, '^\\s*[-*•]')))::DOUBLE / greatest(len({LINES_SQL}), 1) <= 0.9 AND len(list_filter({LINES_SQL}, lambda s: regexp_matches(s, '(…|\\.\\.\\.)\\s*$')))::DOUBLE / greatest(len({LINES_SQL}), 1) <= 0.3
  AND len(list_filter({TOK_T}, lambda s: regexp_matches(s, '[A-Za-zÀ-ÿœ]')))::DOUBLE / greatest(len({TOK_T}), 1) >= 0.8 AND len(list_filter({WORDS_SQL.format(t='text')}, lambda x: list_contains({lst(recipes.ALL_FUNCTION_WORDS)}, x))) >= 2)"""
CLEAN_LINES_SQL = f"""array_to_string(list_filter({LINES_SQL}, lambda s: NOT (length(regexp_replace(s, '[^A-Z]', '', 'g')) * 2 > length(s) OR regexp_matches(s, '^[0-9 .,]+$') OR regexp_matches(s, '^[0-9.,]+[kKmM]? (likes|comments|shares|views)$') OR len({TOKENS_SQL.format(t='s')}) <= 1)), chr(10))"""


@query("w63_recipe_comparison", f"""WITH c AS MATERIALIZED (SELECT d.text, k.kept AS c4, CASE WHEN length(d.text) >= 200 AND len({LINES_SQL.replace('text', 'd.text')}) >= 3 THEN d.text END AS mc4, CASE WHEN {MASSIVE_SQL.replace('(text', '(d.text')} THEN d.text END AS massive FROM documents d JOIN {C4_SQL} k USING (doc_id))
  SELECT 'raw' AS recipe, count(*) AS pages, sum(length(text))::BIGINT AS chars FROM c UNION ALL SELECT 'c4', count(c4), sum(length(c4))::BIGINT FROM c UNION ALL SELECT 'mc4', count(mc4), sum(length(mc4))::BIGINT FROM c UNION ALL SELECT 'massive_web', count(massive), sum(length(massive))::BIGINT FROM c
  UNION ALL SELECT 'line_corrections', count(k), sum(length(k))::BIGINT FROM (SELECT CASE WHEN len({TOKENS_SQL.format(t='j')}) >= 0.95 * len({TOK_T}) THEN j END AS k FROM (SELECT text, {CLEAN_LINES_SQL} AS j FROM documents))
  UNION ALL SELECT 'own_quality', count(*), coalesce(sum(length(text)), 0)::BIGINT FROM documents WHERE NOT {mild_flags('text')}""")
def w63(spark, d):
    t = F.col("text")
    reasons = F.size("reasons") == 0
    docs = quality.annotate(table(spark, d, "documents"), MILD)
    return recipes.compare(docs, {"raw": None, "c4": recipes.c4(t), "mc4": F.when(recipes.multilingual_rule(t), t), "massive_web": F.when(recipes.massive_web(t), t), "line_corrections": recipes.clean_lines(t), "own_quality": F.when(reasons, t)})


PARA_MARKS_SQL = f"(WITH u AS (SELECT doc_id, unnest(range(0, len(u))) AS pos, unnest(u) AS unit FROM (SELECT doc_id, {PARAS_SQL} AS u FROM documents)), f AS (SELECT doc_id, row_number() OVER (PARTITION BY substr(sha1(unit), 1, 16) ORDER BY doc_id, pos) AS rn FROM u) SELECT doc_id, count(*) FILTER (rn = 1) AS kept, count(*) FILTER (rn > 1) AS dropped FROM f GROUP BY doc_id)"


@query("w63e_annotate_only", f"SELECT d.doc_id, d.source, length(d.text)::DOUBLE AS q_length, round({term_sql('d.text', HARMFUL_TERMS)}, 6) AS q_harmful, {mild_flags('d.text')} AS flagged, coalesce(p.kept, 0) AS paragraphs_first, coalesce(p.dropped, 0) AS paragraphs_seen FROM documents d LEFT JOIN {PARA_MARKS_SQL} p ON p.doc_id = d.doc_id")
def w63e(spark, d):
    """Quality signals and paragraph duplicates beside every text; nothing is removed."""
    a = quality.annotate(table(spark, d, "documents"), MILD)
    marks = exact.dedup_paragraphs(table(spark, d, "documents")).select("doc_id", F.col("kept").alias("paragraphs_first"), F.col("dropped").alias("paragraphs_seen"))
    signals = a.select("doc_id", "source", "q_length", r6(F.col("q_harmful")).alias("q_harmful"), (F.size("reasons") > 0).alias("flagged"))
    return signals.join(marks, "doc_id", "left").fillna(0, ["paragraphs_first", "paragraphs_seen"])


@query("w63b_truecase")
def w63b(spark, d):
    return normalize.truecase(table(spark, d, "documents")).select("doc_id", F.md5(F.col("text").cast("binary")).alias("md5"))


@query("w63c_similar_to_reference")
def w63c(spark, d):
    return classifier.similar_to_reference(table(spark, d, "documents"), table(spark, d, "benchmark")).select("doc_id", "p")


@query("w63d_harmful_classifier")
def w63d(spark, d):
    docs = table(spark, d, "documents")
    return classifier.score(docs, classifier.train_harmful(docs, table(spark, d, "labels"))).select("doc_id", "p")


COMPONENT_SQL = "CASE WHEN lang = 'fr' AND source = 'src0' THEN 'encyclopedia' WHEN lang = 'fr' THEN 'target_web' WHEN lang = 'en' THEN 'english_web' WHEN lang = 'de' THEN 'papers' END"


def plan_sql(values: str) -> str:
    return f"""WITH v AS (SELECT component, tokens::DOUBLE AS tokens FROM (VALUES {values}) v(component, tokens)), d AS (SELECT {COMPONENT_SQL} AS component, sum(len({TOK_T}))::BIGINT AS available FROM documents GROUP BY 1)
  SELECT v.component, tokens, round(tokens / 104857600000.0::DOUBLE, 6) AS share, coalesce(available, 0)::BIGINT AS available, round(tokens / nullif(available, 0)::DOUBLE, 3) AS epochs FROM v LEFT JOIN d ON d.component = v.component"""


def planned(spark, d, components) -> DataFrame:
    """The plan of a mixture, and how often the given texts of each component would be read for it."""
    out = mixture.supply(mixture.plan(spark, components), table(spark, d, "documents"), F.size(ts.tokens(F.col("text"))), F.expr(COMPONENT_SQL))
    return out.select("component", "tokens", r6(F.col("share")).alias("share"), "available", F.round("epochs", 3).alias("epochs"))


@query("w64_mixture_plan", plan_sql("('target_web', 0.9::DOUBLE * 104857600000 - 1.6e9), ('encyclopedia', 1.6e9), ('english_web', 0.05::DOUBLE * 104857600000), ('papers', 0.05::DOUBLE * 104857600000)"))
def w64(spark, d):
    return planned(spark, d, mixture.PAPER_PLAN)


@query("w64b_mixture_72_28", plan_sql("('target_web', 0.72::DOUBLE * 104857600000 - 1.6e9), ('encyclopedia', 1.6e9), ('english_web', 0.28::DOUBLE * 104857600000)"))
def w64b(spark, d):
    return planned(spark, d, mixture.SECOND_PLAN)


SHARES = [("fr", 40_000.0), ("de", 20_000.0), ("en", 60_000.0), ("es", 1e12)]


@query("w65_mixture_sample", f"""WITH g AS (SELECT * FROM (VALUES {', '.join(f"('{c}', {g}::DOUBLE)" for c, g in SHARES)}) v(lang, goal)), s AS (SELECT doc_id, lang, len({TOK_T}) AS n, sum(len({TOK_T})) OVER (PARTITION BY lang ORDER BY {UNIT_SQL.format(k='doc_id')}, doc_id ROWS UNBOUNDED PRECEDING) AS run FROM documents)
  SELECT doc_id, lang, n AS tokens FROM s JOIN g USING (lang) WHERE run <= goal""")
def w65(spark, d):
    budgets = spark.createDataFrame(SHARES, "component string, tokens double")
    docs = table(spark, d, "documents").select("doc_id", "lang", F.size(ts.tokens(F.col("text"))).alias("tokens"))
    return mixture.sample(docs, "lang", budgets, F.col("tokens")).select("doc_id", "lang", "tokens")


@query("w66_vocab_candidates", "SELECT gram, count(*) AS n FROM (SELECT substring(t, i::INT, 2) AS gram FROM (SELECT t, unnest(range(1, greatest(length(t) - 1, 1) + 1)) AS i FROM (SELECT lower(text) AS t FROM documents))) WHERE length(gram) = 2 AND gram NOT IN (SELECT DISTINCT substring(t, i::INT, 2) FROM (SELECT t, unnest(range(1, length(t))) AS i FROM (SELECT lower(text) AS t FROM benchmark))) GROUP BY gram ORDER BY n DESC, gram LIMIT 100")
def w66(spark, d):
    base = chargrams.gram_counts(table(spark, d, "benchmark").select(F.lower("text").alias("low")), 2, text="low").select("gram")
    return mixture.vocabulary_candidates(table(spark, d, "documents"), 100, 2, base)


def schedule_sql(peak: str, final: str) -> str:
    return f"""WITH t AS (SELECT least(floor({UNIT_SQL.format(k='doc_id')} * 25001), 25000)::BIGINT AS step, count(*) AS texts FROM documents WHERE doc_id IS NOT NULL GROUP BY 1)
  SELECT i AS step, round(CASE WHEN i < 1000 THEN i * ({peak} / 1000) ELSE {final} + ({peak} - {final}) * (1 + cos(3.141592653589793 * (i - 1000) / 24000.0)) / 2 END * 1e6, 6) AS lr_e6, coalesce(texts, 0)::BIGINT AS texts FROM (SELECT unnest(range(0, 25001)) AS i) LEFT JOIN t ON t.step = i"""


def scheduled(spark, d, **shape) -> DataFrame:
    """The learning rate of every step, and the number of given texts that are dealt to it."""
    out = mixture.texts_by_step(mixture.lr_schedule(spark, **shape), table(spark, d, "documents"))
    return out.select("step", F.round(F.col("lr") * 1e6, 6).alias("lr_e6"), "texts")


@query("w66b_lr_schedule", schedule_sql("1e-4", "1e-4 / 30"))
def w66b(spark, d):
    return scheduled(spark, d)


@query("w66c_lr_schedule_second", schedule_sql("2e-5", "2e-5 / 10"))
def w66c(spark, d):
    return scheduled(spark, d, peak=2e-5, final_ratio=1 / 10)


SCORES_SQL = """WITH j AS (SELECT source, lang, coalesce(try_cast(regexp_extract(source, '([0-9]{1,9})$', 1) AS BIGINT), 0) AS k, sum(quality) AS s, count(*) AS n FROM documents JOIN labels USING (doc_id) WHERE source IS NOT NULL AND lang IS NOT NULL AND quality IS NOT NULL GROUP BY ALL),
  l AS (SELECT source AS model, 'group' || (k % 4) AS size, 'src' || (k % 4) AS base, CASE WHEN k < 4 THEN 'base' ELSE 'continued' END AS role, sum(s) OVER (PARTITION BY source)::DOUBLE * 100 / sum(n) OVER (PARTITION BY source)::DOUBLE AS printed, lang AS task, s::DOUBLE * 100 / n AS score FROM j),
  e AS (SELECT model, base, role, task, score FROM l UNION ALL SELECT DISTINCT model, base, role, 'Avg', printed FROM l),
  g AS (SELECT x.model, x.base, x.task, round(x.score - b.score, 6) AS gain FROM e x JOIN e b ON b.role = 'base' AND b.base = x.base AND b.task = x.task WHERE x.role = 'continued') """


def measured(spark, d) -> DataFrame:
    return tables.measured_scores(table(spark, d, "documents"), table(spark, d, "labels"))


@query("w67_score_average", SCORES_SQL + "SELECT model, round(avg(score), 6) AS mean, printed FROM l GROUP BY model, printed")
def w67(spark, d):
    return tables.averages(measured(spark, d), 6)


@query("w68_score_gain", SCORES_SQL + "SELECT model, task, gain FROM g")
def w68(spark, d):
    return tables.gains(measured(spark, d), 6)


@query("w69_score_best", SCORES_SQL + "SELECT size, task, model FROM (SELECT *, rank() OVER (PARTITION BY size, task ORDER BY score DESC) AS r FROM l) WHERE r = 1")
def w69(spark, d):
    return tables.best_in_group(measured(spark, d))


@query("w70_corpus_comparison", SCORES_SQL + "SELECT model, gain, rank() OVER (ORDER BY gain DESC) AS place FROM g WHERE task = 'Avg' AND base = 'src0'")
def w70(spark, d):
    """The sources of one base by their average gains."""
    return tables.corpus_comparison(measured(spark, d), "base = 'src0'", 6)


@query("w71_catalog_sizes", """WITH s AS (SELECT source, sum(length(text)) FILTER (lang = 'fr') AS t, sum(length(text)) FILTER (lang = 'fr' AND length(text) >= 400) AS c FROM documents WHERE source IS NOT NULL GROUP BY source),
  v AS (SELECT source AS corpus, t::DOUBLE AS size FROM s UNION ALL SELECT 'own-clean', sum(c)::DOUBLE FROM s) SELECT corpus, size AS target_size, rank() OVER (ORDER BY size DESC) AS place, round((SELECT sum(c)::DOUBLE FROM s) / size, 4) AS ratio FROM v WHERE size IS NOT NULL AND (SELECT sum(c) FROM s) IS NOT NULL""")
def w71(spark, d):
    return tables.size_report(tables.measured_catalog(table(spark, d, "documents"), "fr"), "L")


@query("w72_majority_share", "SELECT 'toxic' AS label, max_by(v, n) AS majority, round(max(n) / sum(n)::DOUBLE, 6) AS share FROM (SELECT toxic::VARCHAR AS v, count(*) AS n FROM labels GROUP BY 1) UNION ALL SELECT 'quality', max_by(v, n), round(max(n) / sum(n)::DOUBLE, 6) FROM (SELECT quality::VARCHAR AS v, count(*) AS n FROM labels GROUP BY 1)")
def w72(spark, d):
    labels = table(spark, d, "labels")
    return metrics.majority_share(labels, "toxic").union(metrics.majority_share(labels, "quality")).withColumn("share", r6(F.col("share")))


def wgram_sql(rel: str, key: str) -> str:
    return f"SELECT {key} DISTINCT_ID, array_to_string(w[p + 1 : p + 13], ' ') AS g FROM (SELECT *, unnest(range(0, greatest(len(w) - 12, 0))) AS p FROM (SELECT *, {WORDS_SQL.format(t='text')} AS w FROM {rel}))"


@query("w73_decontamination", f"WITH d AS ({wgram_sql('documents', 'doc_id AS').replace('AS DISTINCT_ID', 'AS id')}), b AS ({wgram_sql('benchmark', 'item_id AS').replace('AS DISTINCT_ID', 'AS id')}) SELECT id AS doc_id, count(DISTINCT g) AS hits FROM d WHERE g IN (SELECT g FROM b) GROUP BY id")
def w73(spark, d):
    return metrics.contamination(table(spark, d, "documents"), table(spark, d, "benchmark"))


@query("w74_scrub_pii", f"SELECT doc_id, len(regexp_extract_all(text, '{recipes.EMAIL}')) AS emails, md5(regexp_replace(regexp_replace(text, '{recipes.EMAIL}', '', 'g'), '{recipes.FRAGMENT}', '', 'g')) AS md5 FROM documents")
def w74(spark, d):
    return table(spark, d, "documents").select("doc_id", F.regexp_count("text", F.lit(recipes.EMAIL)).alias("emails"), F.md5(recipes.scrub(F.col("text")).cast("binary")).alias("md5"))


@query("w74b_punctuation_ascii", "SELECT doc_id, md5(replace(translate(text, '“”„«»‘’‚–—', '\"\"\"\"\"''''''--'), '…', '...')) AS md5 FROM documents")
def w74b(spark, d):
    return table(spark, d, "documents").select("doc_id", F.md5(normalize.punctuation_ascii(F.col("text")).cast("binary")).alias("md5"))


@query("w75_conversation_quality", f"SELECT conv_id, turn, length(text)::DOUBLE AS length, round({term_sql('text', HARMFUL_TERMS)}, 6) AS harmful, len({sentences_sql('text')}) AS sentences FROM conversations")
def w75(spark, d):
    c = table(spark, d, "conversations")
    a = quality.annotate(c, LATIN["en"])
    return a.select("conv_id", "turn", F.col("q_length").alias("length"), r6(F.col("q_harmful")).alias("harmful"), F.size(ts.sentences(F.col("text"))).alias("sentences"))


COS_SQL = "(list_dot_product(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) / (sqrt(list_dot_product(x.embedding::DOUBLE[], x.embedding::DOUBLE[])) * sqrt(list_dot_product(y.embedding::DOUBLE[], y.embedding::DOUBLE[]))))"


@query("w76_embedding_near_dup", f"SELECT x.vec_id AS a, y.vec_id AS b, round({COS_SQL}, 5) AS cosine FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id WHERE x.vec_id % 100 = 0 AND {COS_SQL} >= 0.3")
def w76(spark, d):
    """A search: every vector whose id is divisible by 100, against all vectors, whatever their label."""
    e = table(spark, d, "embeddings")
    return digests.search(e, e.filter("vec_id % 100 = 0"), 0.3).select("a", "b", F.round("cosine", 5).alias("cosine"))


@query("w76b_embedding_near_dup_whole")
def w76b(spark, d):
    return digests.close_pairs(table(spark, d, "embeddings"), 0.9).select("a", "b", F.round("cosine", 5).alias("cosine"))


TURNS = "(SELECT conv_id, turn, text AS gold, lead(text) OVER (PARTITION BY conv_id ORDER BY turn) AS pred FROM conversations)"


def turns(spark, d) -> DataFrame:
    """(conv_id, turn, gold, pred): each turn with the one after it as its answer."""
    t = table(spark, d, "conversations").select("conv_id", "turn", F.col("text").alias("gold"), F.lead("text").over(Window.partitionBy("conv_id").orderBy("turn")).alias("pred"))
    return t.filter("pred IS NOT NULL AND (pred <> '' OR gold <> '')")


@query("w77_answer_metrics", f"""WITH t AS MATERIALIZED (SELECT * FROM {TURNS} WHERE pred IS NOT NULL), c AS (SELECT conv_id, turn, 'p' AS side, unnest(string_split(pred, '')) AS ch FROM t UNION ALL SELECT conv_id, turn, 'g', unnest(string_split(gold, '')) FROM t),
  n AS (SELECT conv_id, turn, ch, count(*) FILTER (side = 'p') AS p, count(*) FILTER (side = 'g') AS g FROM c WHERE ch <> '' GROUP BY ALL), f AS (SELECT conv_id, turn, 2.0 * sum(least(p, g)) / sum(p + g) AS f1 FROM n GROUP BY ALL)
  SELECT t.conv_id, t.turn, (trim(pred) = trim(gold))::INT AS exact_match, round(f1::DOUBLE, 6) AS char_f1 FROM t JOIN f USING (conv_id, turn)""")
def w77(spark, d):
    a = metrics.answer_metrics(turns(spark, d), "pred", "gold")
    return a.select("conv_id", "turn", "exact_match", r6(F.col("char_f1")).alias("char_f1"))


NUMBER_SQL = "regexp_extract_all(replace({t}, ',', ''), '-?[0-9]+(?:\\.[0-9]+)?')"
SPLIT_SQL = "list_filter(regexp_split_to_array({t}, '\\s+'), lambda x: x <> '')"


def clipped_sql(n: int) -> str:
    """(conv_id, turn, hit, total): clipped matches and number of a prediction's word n-grams."""
    def grams(t: str) -> str:
        return f"SELECT conv_id, turn, array_to_string(w[p + 1 : p + {n}], ' ') AS g, count(*) AS c FROM (SELECT conv_id, turn, w, unnest(range(0, greatest(len(w) - {n - 1}, 0))) AS p FROM (SELECT conv_id, turn, {SPLIT_SQL.format(t=t)} AS w FROM t)) GROUP BY ALL"

    return f"(SELECT x.conv_id, x.turn, sum(least(x.c, coalesce(y.c, 0))) AS hit, sum(x.c) AS total FROM ({grams('pred')}) x LEFT JOIN ({grams('gold')}) y ON x.conv_id = y.conv_id AND x.turn = y.turn AND x.g = y.g GROUP BY ALL)"


@query("w77b_answer_metrics_words", f"""WITH t AS MATERIALIZED (SELECT * FROM {TURNS} WHERE pred IS NOT NULL AND (pred <> '' OR gold <> '')),
  m AS (SELECT conv_id, turn, coalesce(({NUMBER_SQL.format(t='pred')}[-1]::DOUBLE = {NUMBER_SQL.format(t='gold')}[-1]::DOUBLE)::INT, 0) AS numeric_match, exp(least(0, 1 - len({SPLIT_SQL.format(t='gold')}) / nullif(len({SPLIT_SQL.format(t='pred')}), 0)::DOUBLE)) AS brevity FROM t)
  SELECT m.conv_id, m.turn, numeric_match, round(coalesce(CASE WHEN least(a.hit, b.hit, c.hit, e.hit) > 0 THEN exp((ln(a.hit / a.total::DOUBLE) + ln(b.hit / b.total::DOUBLE) + ln(c.hit / c.total::DOUBLE) + ln(e.hit / e.total::DOUBLE)) / 4) * brevity END, 0.0), 6) AS ngram_precision
  FROM m LEFT JOIN {clipped_sql(1)} a USING (conv_id, turn) LEFT JOIN {clipped_sql(2)} b USING (conv_id, turn) LEFT JOIN {clipped_sql(3)} c USING (conv_id, turn) LEFT JOIN {clipped_sql(4)} e USING (conv_id, turn)""")
def w77b(spark, d):
    a = metrics.answer_metrics(turns(spark, d), "pred", "gold")
    return a.select("conv_id", "turn", "numeric_match", r6(F.col("ngram_precision")).alias("ngram_precision"))


@query("w77c_answer_metrics_lcs")
def w77c(spark, d):
    a = metrics.answer_metrics(turns(spark, d), "pred", "gold")
    return a.select("conv_id", "turn", r6(F.col("lcs_recall")).alias("lcs_recall"))


@query("w78_sizes", f"SELECT sum(length(text))::BIGINT AS letters, sum(len({TOK_T}))::BIGINT AS words, sum(len(regexp_extract_all(text, '[A-Za-z0-9À-ÿœ]+|[^A-Za-z0-9À-ÿœ \\n\\t\\r]')))::BIGINT AS tokens, sum(strlen(text))::BIGINT AS bytes FROM documents")
def w78(spark, d):
    return metrics.sizes(table(spark, d, "documents"))


def exact_sql(least: float) -> str:
    return jaccard_sql(prefix_sql(least), least)


@query("w79_pair_quality", f"""WITH f AS MATERIALIZED {of_reps(pairs_sql(4, 8))}, t AS MATERIALIZED (SELECT a, b FROM {of_reps(exact_sql(0.8))}), j AS (SELECT (t.a IS NOT NULL) AS t, (f.a IS NOT NULL) AS g FROM f FULL JOIN t ON f.a = t.a AND f.b = t.b) SELECT {CONF_SQL} FROM j""")
def w79(spark, d):
    """Candidates of 4 x 8 hashes against all pairs of different texts of Jaccard 0.8 or more, which are found without hashing.
    Both are counted where they are met, so that no pair is a row.
    """

    def count(a, b, jaccard, da, db):
        return pa.RecordBatch.from_arrays([pa.array([len(jaccard)]), pa.array([int(minhash.share_a_band(da, db, 8).sum())])], names=["pairs", "tp"])

    reps = minhash.representatives(unshuffled(spark, d, "documents"))
    counts = minhash.near_pairs(reps, 0.8, count, "pairs long, tp long", minhash.band_digests(4, 8, family="md5"), like=spark.read.parquet(f"{d}/documents.parquet"))
    true = counts.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("pairs", "tp")])
    found = minhash.count_candidates(minhash.digests(reps, 4, 8, family="md5"), 8)
    return true.crossJoin(found).select("tp", (F.col("n") - F.col("tp")).alias("fp"), (F.col("pairs") - F.col("tp")).alias("fn"), F.lit(0).cast("long").alias("tn"))


BIN = "least(floor(jaccard * 20 + 1e-9), 19) / 20.0"


@query("w79b_recall_by_similarity", f"""WITH f AS MATERIALIZED {of_reps(pairs_sql(4, 8))}, t AS MATERIALIZED (SELECT a, b, round(jaccard, 6) AS jaccard FROM {of_reps(exact_sql(0.5))})
  SELECT round(({BIN})::DOUBLE, 2) AS bin, count(*) AS pairs, count(f.a) AS found, round(count(f.a) / count(*)::DOUBLE, 6) AS recall, round(avg(1 - pow(1 - pow(jaccard, 4), 8)), 6) AS expected FROM t LEFT JOIN f ON f.a = t.a AND f.b = t.b GROUP BY 1""")
def w79b(spark, d):
    """Recall of candidates among true pairs, by similarity, beside what the curve says."""
    return recall_by_similarity(spark, d, 4, 8, "md5")


def recall_by_similarity(spark, d: str, rows: int, bands: int, family: str = "poly") -> DataFrame:
    """Counts of all pairs of Jaccard 0.5 or more, and of those that are candidates, that is, share a band of their signatures.
    Pairs are counted where they are verified; signatures are made of the texts in such pairs only.
    """

    def count(a, b, jaccard, da, db):
        jaccard = np.floor(jaccard * 1e6 + 0.5) / 1e6
        bins = np.minimum(np.floor(jaccard * 20 + 1e-9), 19).astype(np.int64)
        found = minhash.share_a_band(da, db, bands)
        sums = [np.bincount(bins, weights, 20) for weights in (None, found, 1 - (1 - jaccard**rows) ** bands)]
        some = np.flatnonzero(sums[0])
        return pa.RecordBatch.from_arrays([pa.array(some), pa.array(sums[0][some]), pa.array(sums[1][some].astype(np.int64)), pa.array(sums[2][some])], names=["bin", "pairs", "found", "expected"])

    counts = minhash.near_pairs(minhash.representatives(unshuffled(spark, d, "documents")), 0.5, count, "bin long, pairs long, found long, expected double", minhash.band_digests(rows, bands, family=family), like=spark.read.parquet(f"{d}/documents.parquet"))
    out = counts.groupBy("bin").agg(*[F.sum(c).alias(c) for c in ("pairs", "found", "expected")])
    return out.select(F.round(F.col("bin") / F.lit(20.0), 2).alias("bin"), "pairs", "found", r6(F.col("found") / F.col("pairs")).alias("recall"), r6(F.col("expected") / F.col("pairs")).alias("expected"))


@query("w79c_recall_printed_setting")
def w79c(spark, d):
    """The same for the printed 20 x 40 hashes: pairs that share a band of their digests."""
    return recall_by_similarity(spark, d, minhash.ROWS, minhash.BANDS)


@query("w80_corpus_profile", f"SELECT count(*) AS texts, round(avg(length(text)), 6) AS mean_chars, round(avg((length(text) < 400)::INT), 6) AS rate_short, round(avg(({term_sql('text', HARMFUL_TERMS)} > 0)::INT), 6) AS rate_harmful FROM documents")
def w80(spark, d):
    t = F.col("text")
    p = metrics.corpus_profile(table(spark, d, "documents"), {"short": F.length(t) < 400, "harmful": ts.term_share(t, HARMFUL_TERMS) > 0})
    return p.select("texts", *[r6(F.col(c)).alias(c) for c in ("mean_chars", "rate_short", "rate_harmful")])


@query("w81_url_hosts_suffix", f"SELECT page_id, s AS domain FROM (SELECT page_id, unnest(list_transform(range(1, len(l) + 1), lambda i: array_to_string(l[i : len(l)], '.'))) AS s FROM (SELECT page_id, string_split(lower(regexp_extract(url, '^[a-zA-Z]+://([^/?#:]+)', 1)), '.') AS l FROM pages))")
def w81(spark, d):
    p = table(spark, d, "pages").select("page_id", hosts.host_of(F.col("url")).alias("host"))
    return p.select("page_id", F.explode(hosts.suffixes(F.col("host"))).alias("domain"))
