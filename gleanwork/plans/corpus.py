"""Workloads over the paper's own methods: gate, extraction, rules, repetition, harmful terms, deduplication, hosts, cleaning."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from ..functions import textstats as ts
from ..operators import dedup, gate, hosts, htmltext, langid, metrics, minhash, normalize, pipeline, quality, repetition
from ..profiles import BLOCKED_STEMS, ELLIPSES, ENCYCLOPEDIA_SUFFIX, FORUM_SUFFIX, FUNCTION_WORDS, HARMFUL_TERMS, HIRAGANA, JA, KANJI, KATAKANA, LATIN, PUNCTUATION, SITE_TERMS, TERMINATORS, kana_map
from ..sources.archive import from_pages, select_snapshots

Q: dict[str, tuple] = {}
TARGETS = ["fr", "de", "es"]
SMALL_ROWS, SMALL_BANDS = 4, 8  # the setting that SQL can check
GLOBS = [f"*{ENCYCLOPEDIA_SUFFIX}", f"*{FORUM_SUFFIX}"]


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    """A given table; small tables of texts are dealt over all cores."""
    df = spark.read.parquet(f"{d}/{name}.parquet")
    return ts.spread(df) if name in ("documents", "pages") else df


def unshuffled(spark, d: str, name: str) -> DataFrame:
    """A given table whose texts are dealt over the cores only where it has fewer files than there are cores."""
    df = spark.read.parquet(f"{d}/{name}.parquet")
    return df if len(df.inputFiles()) >= spark.sparkContext.defaultParallelism else table(spark, d, name)


def query(name: str, sql: str | None = None):
    def keep(f):
        Q[name] = (f, sql)
        return f

    return keep


def r6(c: Column) -> Column:
    return F.round(c, 6)


# ---------------------------------------------------------------- SQL pieces
def lst(words) -> str:
    return "[" + ",".join("'" + w.replace("'", "''") + "'" for w in words) + "]"


WORDS_SQL = r"regexp_extract_all(lower({t}), '[a-zà-öø-ÿœ]+')"
TOKENS_SQL = r"regexp_extract_all({t}, '[^ \n\t\r]+')"


def score_sql(t: str, code: str) -> str:
    w = WORDS_SQL.format(t=t)
    hit = lambda ws: f"len(list_filter({w}, lambda x: list_contains({lst(ws)}, x)))"
    return f"(CASE WHEN len({w}) = 0 THEN 0.0 ELSE ({hit(langid.own_words(code))} - {hit(langid.foreign_words(code))})::DOUBLE / len({w}) END)"


def decode_sql(t: str) -> str:
    for name, char in gate.ENTITIES:
        t = f"replace({t}, '{name}', '{char.replace(chr(39), chr(39) * 2)}')"
    return t


TITLE_SQL = f"trim(regexp_replace({decode_sql(chr(114) + 'egexp_extract(substring(html,1,65536), ' + chr(39) + '(?is)<title[^>]*>(.*?)</title>' + chr(39) + ', 1)')}, '[ \\t\\r\\n]+', ' ', 'g'))"
DECLARED_SQL = "lower(regexp_extract(substring(html,1,4096), '(?i)<html\\b[^>]*?[\\s\"'']lang\\s*=\\s*[\"'']?([a-z]+)', 1))"
VIEW_SQL = """(SELECT page_id, url, CASE WHEN page_id % 3 = 0 THEN regexp_replace(html, ' lang="[a-z]+"', '', 'g')
  WHEN page_id % 7 = 0 THEN regexp_replace(html, ' lang="[a-z]+"', ' lang="' || translate(regexp_extract(html, ' lang="([a-z]+)"', 1), 'edf', 'fed') || '"', 'g') ELSE html END AS html FROM pages)"""


def sentences_sql(t: str) -> str:
    return f"list_filter(list_transform(regexp_extract_all({t}, '[^{TERMINATORS}\\n]+[{TERMINATORS}]*'), lambda s: trim(s)), lambda s: s <> '')"


def share_sql(t: str, chars: str) -> str:
    return f"(CASE WHEN length({t}) = 0 THEN 0.0 ELSE length(regexp_replace({t}, '[^{chars}]', '', 'g'))::DOUBLE / length({t}) END)"


def kana_sql(t: str = "text", letters: str | None = None, marks: bool = True) -> str:
    a, b = kana_map(marks=marks) if letters is None else kana_map(letters, marks)
    return f"translate({t}, '{a}', '{b}')"


def term_sql(t: str, terms) -> str:
    return f"(CASE WHEN length(lower({t})) = 0 THEN 0.0 ELSE (length(lower({t})) - length(regexp_replace(lower({t}), '{ts.term_pattern(terms)}', '', 'g')))::DOUBLE / length(lower({t})) END)"


HALF = "abcdefghijklm"
_LOW = "abcdefghijklmnopqrstuvwxyz"
ELLIPSIS_SQL = r"(CASE WHEN doc_id % 5 = 0 THEN regexp_replace(text, '([^.\n]+)\.([^.\n]+)\.([^.\n]+)\.', '\1.\2.\3…', 'g') ELSE text END)"
MARKS_SQL = "(" + " OR ".join(f"ends_with(regexp_replace(regexp_replace(s, '[\"''”’」』)）\\]]+$', ''), '([…‥])[.。]$', '\\1'), '{m}')" for m in ELLIPSES) + ")"


@query("w01_gate_declared", f"SELECT page_id, {DECLARED_SQL} AS declared, " + ", ".join(f"{DECLARED_SQL} = '{c}' AS is_{c}" for c in TARGETS) + f" FROM {VIEW_SQL}")
def w01(spark, d):
    v = gate.gate_view(table(spark, d, "pages"))
    return v.select("page_id", gate.declared_language(F.col("html")).alias("declared"), *[gate.declares_language(F.col("html"), c).alias(f"is_{c}") for c in TARGETS])


@query("w02_gate_title", f"SELECT page_id, md5(t) AS title_md5, " + ", ".join(f"t <> '' AND {score_sql('t', c)} > 0.05 AS is_{c}" for c in TARGETS) + f" FROM (SELECT page_id, {TITLE_SQL} AS t FROM {VIEW_SQL})")
def w02(spark, d):
    v = gate.gate_view(table(spark, d, "pages"))
    held = ts.hold(v, _t=gate.title(F.col("html")))
    held = ts.hold(held, _w=ts.words(F.col("_t")))
    return held.select("page_id", F.md5(F.col("_t").cast("binary")).alias("title_md5"), *[((F.col("_t") != "") & (langid.score_of(F.col("_w"), c) > langid.THRESHOLD)).alias(f"is_{c}") for c in TARGETS])


def either_sql(c: str) -> str:
    return f"({DECLARED_SQL} = '{c}' OR ({TITLE_SQL} <> '' AND {score_sql(TITLE_SQL, c)} > 0.05))"


@query("w03_gate_either", "SELECT page_id, " + ", ".join(f"{either_sql(c)} AS is_{c}" for c in TARGETS) + f" FROM {VIEW_SQL}")
def w03(spark, d):
    v, flags = gate.held_gate(gate.gate_view(table(spark, d, "pages")), TARGETS)
    return v.select("page_id", *[f.alias(f"is_{c}") for c, f in flags.items()])


MAIN_SQL = "html"
MAIN_SQL = f"regexp_replace({MAIN_SQL}, '(?s)<!--.*?-->', '', 'g')"
for _tag in htmltext.DROPPED:
    MAIN_SQL = f"regexp_replace({MAIN_SQL}, '(?is)<{_tag}\\b.*?</{_tag}>', '', 'g')"
MAIN_SQL = f"regexp_replace({MAIN_SQL}, '(?is)<div class=\"(ad|menu|share)\">.*?</div>', '', 'g')"
VISIBLE_SQL = "regexp_replace(html, '(?s)<!--.*?-->', '', 'g')"
for _tag in ("script", "style", "title"):
    VISIBLE_SQL = f"regexp_replace({VISIBLE_SQL}, '(?is)<{_tag}\\b.*?</{_tag}>', '', 'g')"


def tidy_sql(t: str, more: str = "") -> str:
    t = f"regexp_replace({t}, '(?i)</?(p|div|h[1-6]|li|ul|ol|br|article|section|footer|tr|table{more})\\b[^>]*>', chr(10), 'g')"
    t = decode_sql(f"regexp_replace({t}, '<[^>]*>', '', 'g')")
    t = f"regexp_replace(regexp_replace({t}, '[ \\t\\r]+', ' ', 'g'), ' ?\\n[ \\n]*', chr(10), 'g')"
    return f"regexp_replace(regexp_replace({t}, '^[ \\n]+', ''), '[ \\n]+$', '')"


MAIN_SQL, VISIBLE_SQL = tidy_sql(MAIN_SQL), tidy_sql(VISIBLE_SQL, "|nav")


@query("w04_gate_accuracy", f"""WITH p AS (SELECT html, {MAIN_SQL} AS body FROM {VIEW_SQL}), f AS (
  {" UNION ALL ".join(f"SELECT '{c}' AS lang, coalesce({score_sql('body', c)} > 0.05, false) AS t, {either_sql(c)} AS g FROM p" for c in TARGETS)}),
  n AS (SELECT lang, count(*) FILTER (t AND g) AS tp, count(*) FILTER (NOT t AND g) AS fp, count(*) FILTER (t AND NOT g) AS fn, count(*) FILTER (NOT t AND NOT g) AS tn FROM f GROUP BY lang)
  SELECT *, round(tp / nullif(tp + fp, 0)::DOUBLE, 6) AS precision, round(tp / nullif(tp + fn, 0)::DOUBLE, 6) AS recall, round(2 * tp / nullif(2 * tp + fp + fn, 0)::DOUBLE, 6) AS f1, round(fn / nullif(tp + fn, 0)::DOUBLE, 6) AS lost FROM n""")
def w04(spark, d):
    v, flags = gate.held_gate(gate.gate_view(table(spark, d, "pages")), TARGETS)
    v = ts.hold(v, _w=ts.words(htmltext.extract_main_text(F.col("html"))))
    rows = F.array(*[F.struct(F.lit(c).alias("lang"), F.coalesce(langid.score_of(F.col("_w"), c) > langid.THRESHOLD, F.lit(False)).alias("t"), flags[c].alias("g")) for c in TARGETS])
    out = metrics.confusion(v.select(F.explode(rows).alias("r")).select("r.*"), F.col("t"), F.col("g"), ["lang"])
    return out.select("lang", "tp", "fp", "fn", "tn", *[r6(F.col(c)).alias(c) for c in ("precision", "recall", "f1", "lost")])


@query("w05_gate_cost", f"""WITH p AS (SELECT length(html) AS n, {DECLARED_SQL} = 'fr' AS dec, ({TITLE_SQL} <> '' AND {score_sql(TITLE_SQL, 'fr')} > 0.05) AS tit FROM {VIEW_SQL}),
  m AS (SELECT 'off' AS mode, count(*) AS pages, sum(n) AS chars FROM p UNION ALL SELECT 'either', count(*), sum(n) FROM p WHERE dec OR tit UNION ALL SELECT 'declared', count(*), sum(n) FROM p WHERE dec UNION ALL SELECT 'title', count(*), sum(n) FROM p WHERE tit)
  SELECT mode, pages, chars::BIGINT AS chars, round((SELECT sum(n) FROM p) / chars::DOUBLE, 6) AS saving FROM m""")
def w05(spark, d):
    v = ts.hold(gate.gate_view(table(spark, d, "pages")), _declared=gate.declares_language(F.col("html"), "fr"), _title=gate.title(F.col("html")), _n=F.length("html"))
    v = ts.hold(v, _titled=(F.col("_title") != "") & langid.is_target(F.col("_title"), "fr"))
    passes = {"off": F.lit(True), "either": F.col("_declared") | F.col("_titled"), "declared": F.col("_declared"), "title": F.col("_titled")}
    one = v.agg(*[F.struct(F.count_if(F.coalesce(p, F.lit(False))).alias("pages"), F.sum(F.when(p, F.col("_n"))).alias("chars")).alias(m) for m, p in passes.items()])
    rows = F.array(*[F.struct(F.lit(m).alias("mode"), F.col(f"{m}.pages").alias("pages"), F.col(f"{m}.chars").alias("chars"), r6(F.col("off.chars") / F.col(f"{m}.chars").cast("double")).alias("saving")) for m in ("off", "either", "declared", "title")])
    return one.select(F.explode(rows).alias("r")).select("r.*")


@query("w05b_gate_speedup")
def w05b(spark, d):
    """(mode, pages, seconds, speedup): extraction and precise detection of one language after the gate, and without it.

    A measurement: seconds differ from run to run. Both modes run once before they are timed.
    """
    pages = table(spark, d, "pages")
    found = {}
    for repeat in range(2):
        for mode in ("off", "either"):
            began = time.perf_counter()
            found[mode] = (pipeline.extract_stage(pages, "fr", mode).agg(F.count("text")).first()[0], time.perf_counter() - began)
    rows = [(mode, n, seconds, metrics.speedup(found["off"][1], seconds)) for mode, (n, seconds) in found.items()]
    return spark.createDataFrame(rows, "mode string, pages long, seconds double, speedup double")


@query("w06_extract_regex", f"SELECT page_id, length(t) AS chars, md5(t) AS md5 FROM (SELECT page_id, {MAIN_SQL} AS t FROM pages)")
def w06(spark, d):
    t = table(spark, d, "pages").select("page_id", htmltext.extract_main_text(F.col("html")).alias("t"))
    return t.select("page_id", F.length("t").alias("chars"), F.md5(F.col("t").cast("binary")).alias("md5"))


@query("w06b_extract_density")
def w06b(spark, d):
    t = htmltext.extract(table(spark, d, "pages"))
    return t.select("page_id", F.length("text").alias("chars"), F.md5(F.col("text").cast("binary")).alias("md5"))


@query("w06c_extract_stopword_density")
def w06c(spark, d):
    t = htmltext.extract(table(spark, d, "pages"), htmltext.by_stopwords)
    return t.select("page_id", F.length("text").alias("chars"), F.md5(F.col("text").cast("binary")).alias("md5"))


@query("w07_visible_text", f"SELECT page_id, length(t) AS chars, md5(t) AS md5 FROM (SELECT page_id, {VISIBLE_SQL} AS t FROM pages)")
def w07(spark, d):
    t = table(spark, d, "pages").select("page_id", htmltext.visible_text(F.col("html")).alias("t"))
    return t.select("page_id", F.length("t").alias("chars"), F.md5(F.col("t").cast("binary")).alias("md5"))


@query("w08_langid_score", "SELECT doc_id, " + ", ".join(f"round({score_sql('text', c)}, 6) AS score_{c}" for c in FUNCTION_WORDS) + " FROM documents")
def w08(spark, d):
    held = ts.hold(table(spark, d, "documents"), _w=ts.words(F.col("text")))
    return held.select("doc_id", *[r6(langid.score_of(F.col("_w"), c)).alias(f"score_{c}") for c in FUNCTION_WORDS])


@query("w08b_langid_trained")
def w08b(spark, d):
    docs = table(spark, d, "documents")
    return langid.apply(docs, langid.train(docs, F.col("lang") == "fr"))


@query("w08d_langid_accuracy")
def w08d(spark, d):
    """Precision and recall of the trained detector for each language, on the texts it was not trained on (odd hashes of ids)."""
    docs = table(spark, d, "documents")
    even = F.pmod(F.xxhash64("doc_id"), F.lit(2)) == 0
    out = None
    for code in FUNCTION_WORDS:
        model = langid.train(docs.filter(even), F.col("lang") == code)
        found = langid.apply(docs.filter(~even).withColumn("k", F.struct("doc_id", "lang")), model, "k")
        part = metrics.confusion(found, F.col("k.lang") == code, F.col("is_target")).select(F.lit(code).alias("lang"), "tp", "fp", "fn", "tn", *[r6(F.col(c)).alias(c) for c in ("precision", "recall", "f1")])
        out = part if out is None else out.union(part)
    return out


@query("w08c_langid_naive_bayes")
def w08c(spark, d):
    docs = table(spark, d, "documents")
    return langid.naive_bayes(docs.join(table(spark, d, "labels").select("doc_id"), "doc_id", "left_semi"), docs)


VOTE_SQL = "list_value(" + ", ".join(f"len(list_filter(w, lambda x: list_contains({lst(ws)}, x)))" for ws in FUNCTION_WORDS.values()) + ")"


@query("w09_langid_confusion", f"""WITH v AS (SELECT lang, {VOTE_SQL} AS n FROM (SELECT lang, {WORDS_SQL.format(t='text')} AS w FROM documents)),
  p AS (SELECT lang, CASE WHEN list_max(n) = 0 OR len(list_filter(n, lambda x: x = list_max(n))) > 1 THEN 'und' ELSE list_extract({lst(FUNCTION_WORDS)}, list_position(n, list_max(n))::INT) END AS predicted FROM v)
  SELECT lang, predicted, count(*) AS n FROM p GROUP BY ALL""")
def w09(spark, d):
    held = ts.hold(table(spark, d, "documents"), _w=ts.words(F.col("text")))
    return held.select("lang", langid.vote_of(F.col("_w")).alias("predicted")).groupBy("lang", "predicted").agg(F.count("*").alias("n"))


@query("w10_language_share", f"SELECT 'documents' AS src, lang, count(*) AS n, round(count(*) / sum(count(*)) OVER ()::DOUBLE, 6) AS share FROM documents GROUP BY lang UNION ALL SELECT 'pages', {DECLARED_SQL}, count(*), round(count(*) / sum(count(*)) OVER ()::DOUBLE, 6) FROM pages GROUP BY 2")
def w10(spark, d):
    a = metrics.language_share(table(spark, d, "documents"), F.col("lang")).select(F.lit("documents").alias("src"), "*")
    b = metrics.language_share(table(spark, d, "pages"), gate.declared_language(F.col("html"))).select(F.lit("pages").alias("src"), "*")
    return a.union(b).withColumn("share", r6(F.col("share")))


def rule_query(name: str, rule: str, view, view_sql: str, value_sql: str, flag_sql: str):
    def f(spark, d):
        t = table(spark, d, "documents").select("doc_id", view().alias("t"))
        v = t.select("doc_id", quality.rule_values(F.col("t"))[rule].alias("value"))
        return v.select("doc_id", r6(F.col("value")).alias("value"), quality.rule_flags({rule: F.col("value")}, JA.thresholds)[rule].alias("flag"))

    Q[name] = (f, f"SELECT doc_id, round(v, 6) AS value, {flag_sql} AS flag FROM (SELECT doc_id, ({value_sql})::DOUBLE AS v FROM (SELECT doc_id, {view_sql} AS t FROM documents))")


SENT_T = sentences_sql("t")
MEAN_SQL = f"CASE WHEN len({SENT_T}) = 0 THEN length(t) ELSE list_sum(list_transform({SENT_T}, lambda s: length(s)))::DOUBLE / len({SENT_T}) END"
LONG_SQL = f"coalesce(list_max(list_transform({SENT_T}, lambda s: length(s))), length(t))"
ELL_SQL = f"CASE WHEN len({SENT_T}) = 0 THEN 0.0 ELSE len(list_filter({SENT_T}, lambda s: {MARKS_SQL}))::DOUBLE / len({SENT_T}) END"
SCRIPT = HIRAGANA + KATAKANA + KANJI + PUNCTUATION
plain, kana = (lambda: F.col("text")), (lambda: ts.kana_view(F.col("text")))
rule_query("w11_rule_length", "length", plain, "text", "length(t)", "v < 400")
rule_query("w12_rule_hiragana", "hiragana", kana, kana_sql(), share_sql("t", HIRAGANA), "v < 0.2")
rule_query("w13_rule_katakana", "katakana", lambda: ts.kana_view(F.translate("text", _LOW, _LOW.upper())), kana_sql(f"translate(text, '{_LOW}', '{_LOW.upper()}')"), share_sql("t", KATAKANA), "v > 0.5")
rule_query("w14_rule_target_script", "script", lambda: ts.kana_view(F.col("text"), HALF), kana_sql("text", HALF), share_sql("t", SCRIPT), "v < 0.5")
rule_query("w15_rule_mean_sentence", "mean_sentence", plain, "text", MEAN_SQL, "v < 20 OR v > 90")
rule_query("w16_rule_longest_sentence", "longest_sentence", plain, "text", LONG_SQL, "v > 200")
rule_query("w17_rule_ellipsis", "ellipsis", lambda: ts.ellipsis_view(F.col("text"), F.col("doc_id")), ELLIPSIS_SQL, ELL_SQL, "v > 0.2")

FLAGS_SQL = f"""(SELECT doc_id, length(t) < 400 AS length, {share_sql('t', HIRAGANA)} < 0.2 AS hiragana, {share_sql('t', KATAKANA)} > 0.5 AS katakana, {share_sql('t', SCRIPT)} < 0.5 AS script,
  ({MEAN_SQL}) NOT BETWEEN 20 AND 90 AS mean_sentence, {LONG_SQL} > 200 AS longest_sentence, ({ELL_SQL}) > 0.2 AS ellipsis, harm > 0.05 AS harmful
  FROM (SELECT doc_id, {kana_sql()} AS t, {term_sql('text', HARMFUL_TERMS)} AS harm FROM documents))"""
ALL_RULES = [*quality.RULES, "harmful"]


def kana_annotated(spark, d) -> DataFrame:
    docs = table(spark, d, "documents")
    a = quality.annotate(docs.select("doc_id", ts.kana_view(F.col("text")).alias("text"), ts.term_share(F.col("text"), HARMFUL_TERMS).alias("h")), JA.tuned())
    harm = F.col("h") > JA.thresholds.max_harmful
    return a.withColumn("reasons", F.concat(F.array_except("reasons", F.array(F.lit("harmful"))), F.when(harm, F.array(F.lit("harmful"))).otherwise(F.array().cast("array<string>"))))


@query("w18_rules_all", "SELECT doc_id, " + "array_to_string(list_filter([" + ", ".join(f"CASE WHEN {r} THEN '{r}' END" for r in ALL_RULES) + f"], lambda x: x IS NOT NULL), ',') AS reasons FROM {FLAGS_SQL}")
def w18(spark, d):
    return kana_annotated(spark, d).select("doc_id", F.array_join("reasons", ",").alias("reasons"))


@query("w19_rules_leave_one_out", " UNION ALL ".join(f"SELECT '{r}' AS rule, count(*) FILTER (NOT ({' OR '.join(x for x in ALL_RULES if x != r)})) AS survivors FROM {FLAGS_SQL}" for r in ALL_RULES))
def w19(spark, d):
    a = kana_annotated(spark, d).agg(*[F.count_if(F.size(F.array_except("reasons", F.array(F.lit(r)))) == 0).alias(r) for r in ALL_RULES])
    return a.unpivot([], ALL_RULES, "rule", "survivors")


@query("w20_rule_overlap_cube", f"SELECT length, mean_sentence, longest_sentence, count(*) AS n FROM {FLAGS_SQL} GROUP BY CUBE (length, mean_sentence, longest_sentence)")
def w20(spark, d):
    a = kana_annotated(spark, d).select(*[F.array_contains("reasons", r).alias(r) for r in ("length", "mean_sentence", "longest_sentence")])
    return a.cube("length", "mean_sentence", "longest_sentence").agg(F.count("*").alias("n"))


@query("w20b_rule_report", f"WITH r AS (SELECT unnest(list_filter([{', '.join(f'''CASE WHEN {r} THEN '{r}' END''' for r in ALL_RULES)}], lambda x: x IS NOT NULL)) AS rule, ({' + '.join(f'{r}::INT' for r in ALL_RULES)}) AS k FROM {FLAGS_SQL}) SELECT rule, count(*) AS hits, count(*) FILTER (k = 1) AS exclusive FROM r GROUP BY rule")
def w20b(spark, d):
    return quality.rule_report(kana_annotated(spark, d))


def units_sql(split: str) -> str:
    return f"list_filter({split}, lambda s: s <> '')"


LINES_SQL, PARAS_SQL = units_sql("string_split(text, chr(10))"), units_sql("regexp_split_to_array(text, '\\n\\s*\\n')")


def dup_sql(units: str) -> str:
    u = units
    return f"SELECT doc_id, CASE WHEN len({u}) = 0 THEN 0.0 ELSE round((len({u}) - len(list_distinct({u})))::DOUBLE / len({u}), 6) END AS fraction, CASE WHEN length(text) = 0 THEN 0.0 ELSE round((coalesce(list_sum(list_transform({u}, lambda s: length(s))), 0) - coalesce(list_sum(list_transform(list_distinct({u}), lambda s: length(s))), 0))::DOUBLE / length(text), 6) END AS chars FROM documents"


@query("w21_repetition_lines", dup_sql(LINES_SQL))
def w21(spark, d):
    u = ts.lines(F.col("text"))
    return table(spark, d, "documents").select("doc_id", r6(repetition.duplicate_fraction(u)).alias("fraction"), r6(repetition.duplicate_chars(u, F.col("text"))).alias("chars"))


@query("w22_repetition_paragraphs", dup_sql(PARAS_SQL))
def w22(spark, d):
    u = ts.paragraphs(F.col("text"))
    return table(spark, d, "documents").select("doc_id", r6(repetition.duplicate_fraction(u)).alias("fraction"), r6(repetition.duplicate_chars(u, F.col("text"))).alias("chars"))


TOK = "(SELECT doc_id, length(text) AS chars, " + TOKENS_SQL.format(t="text") + " AS w FROM documents)"


def grams_sql(n: str, cols: str = "doc_id, chars") -> str:
    return f"SELECT {cols}, unnest(range(0, greatest(len(w) - ({n}) + 1, 0))) AS pos, w FROM {TOK}"


@query("w23_repetition_topngram", " UNION ALL ".join(f"SELECT doc_id, {n} AS n, round(b.c * b.l / chars::DOUBLE, 6) AS share FROM (SELECT doc_id, chars, max({{'c': c, 'l': l}}) AS b FROM (SELECT doc_id, chars, g, count(*) AS c, length(g) AS l FROM (SELECT doc_id, chars, array_to_string(w[pos + 1 : pos + {n}], ' ') AS g FROM ({grams_sql(str(n))})) GROUP BY ALL) GROUP BY doc_id, chars)" for n in (2, 3, 4)))
def w23(spark, d):
    return repetition.top_ngrams(table(spark, d, "documents"), (2, 3, 4)).select("doc_id", "n", r6(F.col("share")).alias("share"))


def dupgram_sql(n: int) -> str:
    return f"""SELECT b.doc_id, {n} AS n, CASE WHEN b.chars = 0 THEN 0.0 ELSE round(coalesce(s.dup, 0)::DOUBLE / b.chars, 6) END AS share FROM {TOK} b LEFT JOIN (
  SELECT c.doc_id, sum(l.n) AS dup FROM (SELECT DISTINCT doc_id, unnest(range(pos, pos + {n})) AS p FROM (
  SELECT doc_id, pos, row_number() OVER (PARTITION BY doc_id, g ORDER BY pos) AS rn FROM (SELECT doc_id, pos, md5(array_to_string(w[pos + 1 : pos + {n}], ' ')) AS g FROM ({grams_sql(str(n))}))) WHERE rn > 1) c
  JOIN (SELECT doc_id, unnest(range(0, len(w))) AS p, unnest(list_transform(w, lambda x: length(x))) AS n FROM {TOK}) l ON l.doc_id = c.doc_id AND l.p = c.p GROUP BY c.doc_id) s ON b.doc_id = s.doc_id"""


@query("w24_repetition_dupngram", " UNION ALL ".join(dupgram_sql(n) for n in (5, 10)))
def w24(spark, d):
    docs = table(spark, d, "documents")
    a, b = (repetition.duplicated_ngrams(docs, n).select("doc_id", F.lit(n).alias("n"), r6(F.col("share")).alias("share")) for n in (5, 10))
    return a.union(b)


@query("w24b_repetition_one_pass", " UNION ALL ".join(dupgram_sql(n) for n in range(5, 11)))
def w24b(spark, d):
    f = repetition.features(table(spark, d, "documents"))
    return f.select("doc_id", F.explode(F.array(*[F.struct(F.lit(n).alias("n"), r6(F.col(f"dup_{n}")).alias("share")) for n in range(5, 11)])).alias("r")).select("doc_id", "r.*")


@query("w25_harmful_share", f"SELECT doc_id, round(s, 6) AS share, s > 0.05 AS flag FROM (SELECT doc_id, {term_sql('text', HARMFUL_TERMS)} AS s FROM documents)")
def w25(spark, d):
    s = ts.term_share(F.col("text"), HARMFUL_TERMS)
    return table(spark, d, "documents").select("doc_id", r6(s).alias("share"), (s > 0.05).alias("flag"))


CONF_SQL = "count(*) FILTER (t AND g) AS tp, count(*) FILTER (NOT t AND g) AS fp, count(*) FILTER (t AND NOT g) AS fn, count(*) FILTER (NOT t AND NOT g) AS tn"


@query("w26_harmful_vs_labels", f"""WITH f AS (SELECT cut, toxic = 1 AS t, s > cut AS g FROM (SELECT toxic, {term_sql('text', HARMFUL_TERMS)} AS s FROM documents JOIN labels USING (doc_id)), (VALUES (0.0), (0.01), (0.05)) v(cut)),
  n AS (SELECT cut::DOUBLE AS cut, {CONF_SQL} FROM f GROUP BY cut) SELECT *, round(tp / nullif(tp + fp, 0)::DOUBLE, 6) AS precision, round(tp / nullif(tp + fn, 0)::DOUBLE, 6) AS recall FROM n""")
def w26(spark, d):
    j = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").select("toxic", ts.term_share(F.col("text"), HARMFUL_TERMS).alias("s"))
    j = j.select("toxic", "s", F.explode(F.array(F.lit(0.0), F.lit(0.01), F.lit(0.05))).alias("cut"))
    c = metrics.confusion(j, F.col("toxic") == 1, F.col("s") > F.col("cut"), ["cut"])
    return c.select("cut", "tp", "fp", "fn", "tn", r6(F.col("precision")).alias("precision"), r6(F.col("recall")).alias("recall"))


MILD = LATIN["en"].tuned(max_sentence=499, max_harmful=0.01)


def mild_flags(t: str) -> str:
    sent = sentences_sql(t)
    mean = f"CASE WHEN len({sent}) = 0 THEN length({t}) ELSE list_sum(list_transform({sent}, lambda s: length(s)))::DOUBLE / len({sent}) END"
    longest = f"coalesce(list_max(list_transform({sent}, lambda s: length(s))), length({t}))"
    ell = f"CASE WHEN len({sent}) = 0 THEN 0.0 ELSE len(list_filter({sent}, lambda s: {MARKS_SQL}))::DOUBLE / len({sent}) END"
    return f"(length({t}) < 400 OR ({mean}) NOT BETWEEN 20 AND 90 OR {longest} > 499 OR ({ell}) > 0.2 OR {term_sql(t, HARMFUL_TERMS)} > 0.01)"


def of_relation(sql: str, rel: str, key: str) -> str:
    """A piece of SQL over documents and doc_id, over another relation and key."""
    return sql.replace("documents", rel).replace("doc_id", key)


def repetitive_sql(rel: str = "documents", key: str = "doc_id") -> str:
    """Keys of the texts that one of the repetition statistics removes."""
    t = repetition.THRESHOLDS
    top = "SELECT doc_id FROM (SELECT doc_id, chars, max({{'c': c, 'l': l}}) AS b FROM (SELECT doc_id, chars, g, count(*) AS c, length(g) AS l FROM (SELECT doc_id, chars, array_to_string(w[pos + 1 : pos + {n}], ' ') AS g FROM ({grams})) GROUP BY ALL) GROUP BY doc_id, chars) WHERE b.c * b.l / chars::DOUBLE > {most}"
    parts = [f"SELECT doc_id FROM ({dup_sql(u)}) WHERE fraction > {t[f'dup_{n}s']} OR chars > {t[f'dup_{n}_chars']}" for n, u in (("line", LINES_SQL), ("paragraph", PARAS_SQL))]
    parts += [top.format(n=n, grams=grams_sql(str(n)), most=t[f"top_{n}"]) for n in (2, 3, 4)]
    parts += [f"SELECT doc_id FROM ({dupgram_sql(n)}) WHERE share > {t[f'dup_{n}']}" for n in range(5, 11)]
    return of_relation("(" + " UNION ".join(parts) + ")", rel, key)


MILD_SQL = f"(SELECT * FROM documents WHERE NOT {mild_flags('text')} AND doc_id NOT IN {repetitive_sql()})"


@query("w27_quality_stage", f"SELECT 'raw' AS stage, count(*) AS pages, sum(length(text))::BIGINT AS chars FROM documents UNION ALL SELECT 'quality', count(*), sum(length(text))::BIGINT FROM {MILD_SQL}")
def w27(spark, d):
    docs = table(spark, d, "documents")
    return metrics.stage_sizes([("raw", docs), ("quality", dedup.save(pipeline.quality_stage(docs, MILD), "quality"))]).drop("ix")


@query("w27c_quality_stage_rules_only", f"SELECT 'raw' AS stage, count(*) AS pages, sum(length(text))::BIGINT AS chars FROM documents UNION ALL SELECT 'quality', count(*), sum(length(text))::BIGINT FROM documents WHERE NOT {mild_flags('text')}")
def w27c(spark, d):
    docs = table(spark, d, "documents")
    return metrics.stage_sizes([("raw", docs), ("quality", pipeline.quality_stage(docs, MILD, with_repetition=False))]).drop("ix")


@query("w27b_quality_stage_whole")
def w27b(spark, d):
    docs = table(spark, d, "documents")
    return metrics.stage_sizes([("raw", docs), ("quality", pipeline.quality_stage(docs, MILD))]).drop("ix")


# ---------------------------------------------------------------- deduplication
SHINGLES_SQL = "(SELECT DISTINCT doc_id, ('0x' || substr(md5(g), 1, 7))::BIGINT AS h FROM (SELECT doc_id, substring(text, i::INT, 5) AS g FROM (SELECT doc_id, text, unnest(range(1, greatest(length(text) - 4, 1) + 1)) AS i FROM documents WHERE length(text) > 0)))"


@query("w28_shingle_count", f"SELECT doc_id, count(*) AS n FROM {SHINGLES_SQL} GROUP BY doc_id")
def w28(spark, d):
    return minhash.shingle_rows(table(spark, d, "documents")).select("doc_id", F.size("hs").cast("long").alias("n")).filter("n > 0")


def sig_sql(rows: int, bands: int) -> str:
    a, b = minhash.coefficients(rows * bands)
    mins = ", ".join(f"min(({int(x)} * h + {int(y)}) % {minhash.PRIME})" for x, y in zip(a, b))
    return f"(SELECT doc_id, list_value({mins}) AS sig FROM {SHINGLES_SQL} GROUP BY doc_id)"


def keys_sql(rows: int, bands: int) -> str:
    return f"(SELECT doc_id, band, md5(array_to_string(sig[band * {rows} + 1 : band * {rows} + {rows}], ',')) AS bucket FROM (SELECT doc_id, sig, unnest(range(0, {bands}))::INT AS band FROM {sig_sql(rows, bands)}))"


def pairs_sql(rows: int, bands: int) -> str:
    return f"(WITH k AS MATERIALIZED {keys_sql(rows, bands)} SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM k x JOIN k y ON x.band = y.band AND x.bucket = y.bucket AND x.doc_id < y.doc_id)"


def small_sigs(spark, d, rows=SMALL_ROWS, bands=SMALL_BANDS) -> DataFrame:
    return minhash.signatures(table(spark, d, "documents"), rows, bands, family="md5")


def small_keys(spark, d, rows=SMALL_ROWS, bands=SMALL_BANDS) -> DataFrame:
    return minhash.band_keys(small_sigs(spark, d, rows, bands), rows, bands)


@query("w29_minhash_signature", f"SELECT doc_id, array_to_string(sig, ',') AS sig FROM {sig_sql(4, 8)}")
def w29(spark, d):
    return small_sigs(spark, d).select("doc_id", F.array_join("sig", ",").alias("sig"))


@query("w29b_signature_800")
def w29b(spark, d):
    return minhash.signatures(table(spark, d, "documents")).select("doc_id", F.md5(F.array_join("sig", ",").cast("binary")).alias("sig_md5"))


@query("w29c_signature_one_permutation")
def w29c(spark, d):
    return minhash.signatures(table(spark, d, "documents"), one_pass=True).select("doc_id", F.md5(F.array_join("sig", ",").cast("binary")).alias("sig_md5"))


@query("w30_band_keys", f"SELECT doc_id, band, bucket FROM {keys_sql(4, 8)}")
def w30(spark, d):
    return small_keys(spark, d)


REPS_SQL = "(SELECT min(doc_id) AS doc_id, text FROM documents WHERE length(text) > 0 GROUP BY text)"


def members_sql(columns: str = "") -> str:
    """(rep, member) of equal texts, as pairs."""
    return f"(SELECT rep AS a, doc_id AS b{columns} FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS rep FROM documents WHERE length(text) > 0) WHERE rep < doc_id)"


def of_reps(sql: str) -> str:
    return sql.replace("FROM documents", f"FROM {REPS_SQL}")


def rep_keys(spark, d, rows=SMALL_ROWS, bands=SMALL_BANDS) -> DataFrame:
    """Band keys of the texts that stand for their copies; the signatures, not the texts, are joined."""
    docs = table(spark, d, "documents")
    reps = minhash.copies(docs).filter("doc_id = rep").select("doc_id")
    return minhash.band_keys(minhash.signatures(docs, rows, bands, family="md5").join(reps, "doc_id", "left_semi"), rows, bands)


@query("w31_candidates", f"SELECT a, b FROM {of_reps(pairs_sql(4, 8))} UNION ALL SELECT a, b FROM {members_sql()}")
def w31(spark, d):
    """Pairs of different texts, and each copy beside its representative."""
    return minhash.with_members(minhash.candidate_pairs(rep_keys(spark, d)), table(spark, d, "documents"))


def jaccard_sql(pairs: str, least: float) -> str:
    return f"""(WITH p AS MATERIALIZED (SELECT * FROM {pairs}), s AS MATERIALIZED {SHINGLES_SQL}, n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
  c AS (SELECT p.a, p.b, count(*) AS c FROM p JOIN s x ON x.doc_id = p.a JOIN s y ON y.doc_id = p.b AND y.h = x.h GROUP BY ALL)
  SELECT a, b, c / (x.n + y.n - c)::DOUBLE AS jaccard FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE c / (x.n + y.n - c)::DOUBLE >= {least})"""


@query("w32_verified_pairs", f"SELECT a, b, round(jaccard, 6) AS jaccard FROM {of_reps(jaccard_sql(pairs_sql(4, 8), 0.9))} UNION ALL SELECT a, b, jaccard FROM {members_sql(', 1.0::DOUBLE AS jaccard')}")
def w32(spark, d):
    docs = spark.read.parquet(f"{d}/documents.parquet")
    found = minhash.exact_pairs(minhash.representatives(unshuffled(spark, d, "documents")), 0.9, like=docs, sharing=(SMALL_ROWS, SMALL_BANDS, "md5"))
    return minhash.with_members(found.withColumn("jaccard", r6(F.col("jaccard"))), docs, jaccard=1.0)


def prefix_sql(least: float) -> str:
    """Pairs that share one of their rarest shingles: all pairs of Jaccard least or more are among them."""
    return f"""(WITH s AS MATERIALIZED {SHINGLES_SQL}, f AS (SELECT h, count(*) AS f FROM s GROUP BY h), r AS (SELECT s.doc_id, s.h, row_number() OVER (PARTITION BY s.doc_id ORDER BY f, s.h) AS rn, count(*) OVER (PARTITION BY s.doc_id) AS n FROM s JOIN f USING (h)),
  x AS MATERIALIZED (SELECT doc_id, h FROM r WHERE rn <= n - ceil(n * {least}) + 1) SELECT DISTINCT p.doc_id AS a, q.doc_id AS b FROM x p JOIN x q ON p.h = q.h AND p.doc_id < q.doc_id)"""


@query("w33_exact_jaccard_pairs", f"SELECT a, b, round(jaccard, 6) AS jaccard FROM {of_reps(jaccard_sql(prefix_sql(0.8), 0.8))} UNION ALL SELECT a, b, jaccard FROM {members_sql(', 1.0::DOUBLE AS jaccard')}")
def w33(spark, d):
    docs = spark.read.parquet(f"{d}/documents.parquet")
    found = minhash.exact_pairs(minhash.representatives(unshuffled(spark, d, "documents")), 0.8, like=docs)
    return minhash.with_members(found.withColumn("jaccard", r6(F.col("jaccard"))), docs, jaccard=1.0)


def crawled(spark, d) -> DataFrame:
    ix, when = dedup.recency(F.col("doc_id"))
    return table(spark, d, "documents").withColumns({"snapshot_ix": ix, "crawl_ts": when})


LOSERS_SQL = f"(SELECT DISTINCT doc_id FROM (SELECT doc_id, {{'s': doc_id % 21, 'i': doc_id}} AS o, max({{'s': doc_id % 21, 'i': doc_id}}) OVER (PARTITION BY band, bucket) AS m FROM {keys_sql(4, 8)}) WHERE o < m)"


@query("w34_dedup_pairwise", f"SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM {LOSERS_SQL})")
def w34(spark, d):
    return dedup.run(crawled(spark, d), SMALL_BANDS, SMALL_ROWS, family="md5").select("doc_id")


@query("w34b_dedup_printed_setting")
def w34b(spark, d):
    return dedup.run(crawled(spark, d)).select("doc_id")


@query("w34c_dedup_printed_probability")
def w34c(spark, d):
    return dedup.run(crawled(spark, d), bands=20).select("doc_id")


@query("w35_dedup_component", f"""WITH RECURSIVE p AS MATERIALIZED (SELECT * FROM {pairs_sql(4, 8)}), e AS MATERIALIZED (SELECT a, b FROM p UNION SELECT b, a FROM p), r(x, y) AS (SELECT a, a FROM e UNION SELECT r.x, e.b FROM r JOIN e ON e.a = r.y),
  c AS (SELECT x, min(y) AS root FROM r GROUP BY x), m AS (SELECT x, root, max({{'s': x % 21, 'i': x}}) OVER (PARTITION BY root) AS best FROM c)
  SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT x FROM m WHERE best.i <> x)""")
def w35(spark, d):
    return dedup.run(crawled(spark, d), SMALL_BANDS, SMALL_ROWS, family="md5", mode="component").select("doc_id")


@query("w36_dedup_greedy")
def w36(spark, d):
    return dedup.run(crawled(spark, d), SMALL_BANDS, SMALL_ROWS, family="md5", mode="greedy").select("doc_id")


@query("w37_lsh_curve", f"""WITH t AS (SELECT list_distinct({TOKENS_SQL.format(t='text')}) AS x, list_distinct(lead({TOKENS_SQL.format(t='text')}) OVER (PARTITION BY conv_id ORDER BY turn)) AS y FROM conversations),
  j AS (SELECT len(list_intersect(x, y)) AS c, len(x) + len(y) AS n FROM t WHERE x IS NOT NULL AND y IS NOT NULL), b AS (SELECT least(floor(c::DOUBLE / (n - c) * 20 + 1e-9), 19)::DOUBLE / 20 AS s, count(*) AS pairs FROM j WHERE n > 0 GROUP BY 1)
  SELECT rows, bands, s, pairs, round(1 - pow(1 - pow(s, rows), bands), 6) AS p FROM b, (VALUES (20, 40), (20, 20)) v(rows, bands)""")
def w37(spark, d):
    """Neighbouring turns of conversations by similarity of their words, and how likely bands find pairs of that similarity."""
    w = ts.hold(table(spark, d, "conversations").select("conv_id", "turn", "text"), x=ts.tokens(F.col("text"))).select("conv_id", "turn", "x")
    t = w.select("x", F.lead("x").over(Window.partitionBy("conv_id").orderBy("turn")).alias("y")).filter("x IS NOT NULL AND y IS NOT NULL")
    j = t.select(F.size(F.array_intersect("x", "y")).alias("c"), F.size(F.array_union("x", "y")).alias("u")).filter("u > 0")
    s = j.groupBy((F.least(F.floor(F.col("c") / F.col("u") * 20 + 1e-9), F.lit(19)) / F.lit(20.0)).cast("double").alias("s")).agg(F.count("*").alias("pairs"))
    t = s.select("s", "pairs", F.explode(F.array(F.lit(40), F.lit(20))).alias("bands")).withColumn("rows", F.lit(20))
    return t.select("rows", "bands", "s", "pairs", r6(minhash.detection_probability(F.col("s"), F.col("rows"), F.col("bands"))).alias("p"))


@query("w38_survival_by_snapshot", f"SELECT doc_id % 21 AS snapshot_ix, count(*) AS pages, count(*) FILTER (doc_id NOT IN (SELECT doc_id FROM {LOSERS_SQL})) AS kept, round(count(*) FILTER (doc_id NOT IN (SELECT doc_id FROM {LOSERS_SQL})) / count(*)::DOUBLE, 6) AS rate FROM documents GROUP BY 1")
def w38(spark, d):
    c = crawled(spark, d)
    s = dedup.survival_by(c, dedup.run(c, SMALL_BANDS, SMALL_ROWS, family="md5"), "snapshot_ix")
    return s.select(F.col("snapshot_ix").cast("long").alias("snapshot_ix"), "pages", "kept", r6(F.col("rate")).alias("rate"))


@query("w38b_snapshot_selection", "SELECT page_id, page_id % 21 AS snapshot_ix FROM pages WHERE page_id % 21 BETWEEN 15 AND 20")
def w38b(spark, d):
    return select_snapshots(from_pages(table(spark, d, "pages")), 15, 20).select("page_id", F.col("snapshot_ix").cast("long").alias("snapshot_ix"))


# ---------------------------------------------------------------- hosts and cleaning
HOST_SQL = "lower(regexp_extract(url, '^[a-zA-Z]+://([^/?#:]+)', 1))"
HOSTED_SQL = f"(SELECT page_id, {HOST_SQL} AS host, {MAIN_SQL} AS text FROM pages)"


def hosted(spark, d) -> DataFrame:
    return table(spark, d, "pages").select("page_id", hosts.host_of(F.col("url")).alias("host"), htmltext.extract_main_text(F.col("html")).alias("text"))


@query("w39_host_term_share", f"SELECT host, count(*) AS pages, round(avg(regexp_matches(lower(text), '{ts.term_pattern(SITE_TERMS)}')::DOUBLE), 6) AS site, round(avg(regexp_matches(lower(text), '{ts.term_pattern(HARMFUL_TERMS)}')::DOUBLE), 6) AS ng FROM {HOSTED_SQL} GROUP BY host")
def w39(spark, d):
    h = hosted(spark, d)
    site = hosts.term_page_share(h, SITE_TERMS).withColumnRenamed("share", "site")
    ng = hosts.term_page_share(h, HARMFUL_TERMS).select("host", F.col("share").alias("ng"))
    return site.join(ng, "host").select("host", "pages", r6(F.col("site")).alias("site"), r6(F.col("ng")).alias("ng"))


LISTED = [f"{s}.example.{t}" for s in BLOCKED_STEMS for t in ("com", "org", "net")]
BLOCK_SQL = f"""(SELECT host, pages, list_filter([CASE WHEN len(list_filter({lst(LISTED)}, lambda x: host = x OR ends_with(host, '.' || x))) > 0 THEN 'listed' END, CASE WHEN site > 0.001 THEN 'site_terms' END, CASE WHEN ng > 0.005 THEN 'ng_terms' END,
  {", ".join(f"CASE WHEN ends_with(host, '{g[1:]}') THEN 'glob {g}' END" for g in GLOBS)}], lambda x: x IS NOT NULL) AS reasons FROM (SELECT host, count(*) AS pages, avg(regexp_matches(lower(text), '{ts.term_pattern(SITE_TERMS)}')::DOUBLE) AS site, avg(regexp_matches(lower(text), '{ts.term_pattern(HARMFUL_TERMS)}')::DOUBLE) AS ng FROM {HOSTED_SQL} GROUP BY host))"""


def block(spark, h: DataFrame) -> DataFrame:
    listed = spark.createDataFrame([(x,) for x in LISTED], "domain string")
    return hosts.build_blocklist(h, listed, SITE_TERMS, HARMFUL_TERMS, GLOBS)


@query("w40_host_blocklist", f"SELECT host, pages, array_to_string(reasons, ',') AS reasons FROM {BLOCK_SQL} WHERE len(reasons) > 0")
def w40(spark, d):
    return block(spark, hosted(spark, d)).select("host", "pages", F.array_join("reasons", ",").alias("reasons"))


@query("w40b_host_report", f"SELECT r AS reason, count(*) AS hosts, sum(pages)::BIGINT AS pages FROM (SELECT pages, unnest(reasons) AS r FROM {BLOCK_SQL}) GROUP BY r")
def w40b(spark, d):
    return hosts.report(block(spark, hosted(spark, d)))


@query("w41_host_filter", f"SELECT page_id FROM {HOSTED_SQL} WHERE host NOT IN (SELECT host FROM {BLOCK_SQL} WHERE len(reasons) > 0)")
def w41(spark, d):
    h = hosted(spark, d)
    return hosts.apply(h, block(spark, h)).select("page_id")


TIGHT_SQL = kana_sql("replace(text, ' ', '')", marks=False)


def punct_sql(t: str) -> str:
    ja = f"[{HIRAGANA}{KATAKANA}{KANJI}]"
    t = f"translate({t}, '，．', '、。')"
    for mark, ideographic in normalize.BETWEEN:
        for _ in range(2):
            t = f"regexp_replace({t}, '({ja}){mark}({ja})', '\\1{ideographic}\\2', 'g')"
    return t


def footer_sql(t: str) -> str:
    pattern = normalize.footer_pattern().replace("'", "''")
    for _ in range(5):
        t = f"regexp_replace({t}, '{pattern}', '')"
    return t


@query("w42_punctuation", f"SELECT doc_id, md5({punct_sql(TIGHT_SQL)}) AS md5 FROM documents")
def w42(spark, d):
    tight = ts.kana_view(F.replace("text", F.lit(" "), F.lit("")), marks=False)
    return table(spark, d, "documents").select("doc_id", F.md5(normalize.punctuation(tight).cast("binary")).alias("md5"))


@query("w43_footer", f"SELECT doc_id, length(t) AS chars, md5(t) AS md5 FROM (SELECT doc_id, {footer_sql('text')} AS t FROM documents)")
def w43(spark, d):
    t = table(spark, d, "documents").select("doc_id", normalize.trim_footer(F.col("text")).alias("t"))
    return t.select("doc_id", F.length("t").alias("chars"), F.md5(F.col("t").cast("binary")).alias("md5"))


@query("w44_clean_invariants", f"SELECT count(*) AS pages, count(*) FILTER (c = '') AS emptied, sum(length(k))::BIGINT AS chars_before, sum(length(c))::BIGINT AS chars_after FROM (SELECT k, {footer_sql(punct_sql('k'))} AS c FROM (SELECT {TIGHT_SQL} AS k FROM documents UNION ALL SELECT text FROM documents))")
def w44(spark, d):
    docs = table(spark, d, "documents")
    k = docs.select(ts.kana_view(F.replace("text", F.lit(" "), F.lit("")), marks=False).alias("k")).union(docs.select("text"))
    c = normalize.run(k.withColumn("text", F.col("k")))
    return c.agg(F.count("*").alias("pages"), F.count_if(F.col("text") == "").alias("emptied"), F.sum(F.length("k")).alias("chars_before"), F.sum(F.length("text")).alias("chars_after"))


FUNNEL_SQL = f"""WITH q AS MATERIALIZED {MILD_SQL}, k AS MATERIALIZED (SELECT * FROM {keys_sql(4, 8)} WHERE doc_id IN (SELECT doc_id FROM q)),
  l AS (SELECT DISTINCT doc_id FROM (SELECT doc_id, {{'s': doc_id % 21, 'i': doc_id}} AS o, max({{'s': doc_id % 21, 'i': doc_id}}) OVER (PARTITION BY band, bucket) AS m FROM k) WHERE o < m),
  dd AS MATERIALIZED (SELECT * FROM q WHERE doc_id NOT IN (SELECT doc_id FROM l)), b AS (SELECT source FROM dd GROUP BY source HAVING avg(regexp_matches(lower(text), '{ts.term_pattern(SITE_TERMS)}')::DOUBLE) > 0.02),
  h AS MATERIALIZED (SELECT * FROM dd WHERE source NOT IN (SELECT source FROM b)),
  s AS (SELECT 0 AS ix, 'raw' AS stage, count(*) AS pages, sum(length(text))::BIGINT AS chars FROM documents UNION ALL SELECT 1, 'quality', count(*), sum(length(text))::BIGINT FROM q UNION ALL SELECT 2, 'dedup', count(*), sum(length(text))::BIGINT FROM dd UNION ALL SELECT 3, 'hosts', count(*), coalesce(sum(length(text)), 0)::BIGINT FROM h UNION ALL SELECT 4, 'clean', count(*), coalesce(sum(length({footer_sql(punct_sql('text'))})), 0)::BIGINT FROM h)
  SELECT ix, stage, pages, chars, round(pages / lag(pages) OVER (ORDER BY ix)::DOUBLE, 6) AS page_ratio, round(chars / lag(chars) OVER (ORDER BY ix)::DOUBLE, 6) AS char_ratio, round(pages / first(pages) OVER (ORDER BY ix)::DOUBLE, 6) AS page_total, round(chars / first(chars) OVER (ORDER BY ix)::DOUBLE, 6) AS char_total, round(chars / nullif(pages, 0)::DOUBLE, 6) AS chars_per_page FROM s"""


@query("w45_funnel", FUNNEL_SQL)
def w45(spark, d):
    docs = crawled(spark, d)
    listed = lambda dd: hosts.term_page_share(dd, SITE_TERMS, "source").filter("share > 0.02")
    funnel = metrics.funnel_ratios(metrics.stage_sizes([("raw", docs), *whole(docs, "doc_id", "source", listed, SMALL_ROWS, SMALL_BANDS, "md5")]))
    return funnel.select("ix", "stage", "pages", "chars", *[r6(F.col(c)).alias(c) for c in ("page_ratio", "char_ratio", "page_total", "char_total", "chars_per_page")])


def whole(df: DataFrame, key: str, host: str, blocklist_of, rows: int = minhash.ROWS, bands: int = minhash.BANDS, family: str = "poly") -> list[tuple[str, DataFrame]]:
    """Every stage with nothing left out: rules and repetition, newest-wins deduplication, hosts, cleaning."""
    q = dedup.save(pipeline.quality_stage(df, MILD, key), "quality")
    dd = dedup.save(dedup.run(q, bands, rows, key=key, family=family), "dedup")
    h = dedup.save(hosts.apply(dd, blocklist_of(dd), host), "hosts")
    return [("quality", q), ("dedup", dd), ("hosts", h), ("clean", normalize.run(h))]


@query("w45b_funnel_printed_setting")
def w45b(spark, d):
    """The printed hashes and the printed host criteria, all five, over sources as hosts."""
    docs = crawled(spark, d)
    listed = lambda dd: block(spark, dd.select("doc_id", F.col("source").alias("host"), "text")).withColumnRenamed("host", "source")
    return metrics.funnel_ratios(metrics.stage_sizes([("raw", docs), *whole(docs, "doc_id", "source", listed)]))


@query("w45c_funnel_whole")
def w45c(spark, d):
    docs = crawled(spark, d)
    listed = lambda dd: hosts.term_page_share(dd, SITE_TERMS, "source").filter("share > 0.02")
    return metrics.funnel_ratios(metrics.stage_sizes([("raw", docs), *whole(docs, "doc_id", "source", listed)]))


PAGE_LOSERS_SQL = of_relation(LOSERS_SQL, "q", "page_id")


@query("w46_pages_pipeline", f"""WITH v AS (SELECT * FROM {VIEW_SQL} WHERE {either_sql('fr')}), x AS MATERIALIZED (SELECT page_id, {HOST_SQL} AS host, {MAIN_SQL} AS text FROM v), p AS MATERIALIZED (SELECT * FROM x WHERE {score_sql('text', 'fr')} > 0.05),
  q AS MATERIALIZED (SELECT * FROM p WHERE NOT {mild_flags('text')} AND page_id NOT IN {repetitive_sql('p', 'page_id')}), dd AS MATERIALIZED (SELECT * FROM q WHERE page_id NOT IN {PAGE_LOSERS_SQL}),
  h AS (SELECT * FROM dd WHERE host NOT IN (SELECT host FROM {BLOCK_SQL} WHERE len(reasons) > 0)),
  s AS (SELECT 0 AS ix, 'gate' AS stage, text FROM x UNION ALL SELECT 1, 'precise', text FROM p UNION ALL SELECT 2, 'quality', text FROM q UNION ALL SELECT 3, 'dedup', text FROM dd UNION ALL SELECT 4, 'hosts', text FROM h UNION ALL SELECT 5, 'clean', {footer_sql(punct_sql('text'))} FROM h),
  n AS (SELECT unnest(range(0, 6))::INT AS ix, unnest(['gate', 'precise', 'quality', 'dedup', 'hosts', 'clean']) AS stage)
  SELECT n.ix, n.stage, count(s.text) AS pages, coalesce(sum(length(s.text)), 0)::BIGINT AS chars FROM n LEFT JOIN s ON s.ix = n.ix GROUP BY n.ix, n.stage""")
def w46(spark, d):
    """The whole way from pages to clean texts, with hashes that SQL can check: gate, extraction, detection, rules and
    repetition, newest-wins deduplication, five host criteria, cleaning."""
    return pages_pipeline(spark, d, SMALL_ROWS, SMALL_BANDS, "md5")


def pages_pipeline(spark, d, *hashes) -> DataFrame:
    ix, when = dedup.recency(F.col("page_id"))
    v = gate.gate_view(table(spark, d, "pages")).withColumns({"host": hosts.host_of(F.col("url")), "crawl_ts": when})
    x = dedup.save(ts.hold(gate.rapid_gate(v, "fr"), text=htmltext.extract_main_text(F.col("html"))).drop("html"), "gated")
    p = dedup.save(langid.in_language(x, "fr"), "precise")
    return metrics.stage_sizes([("gate", x), ("precise", p), *whole(p, "page_id", "host", lambda dd: block(spark, hosted(spark, d)), *hashes)])


@query("w46d_pages_pipeline_whole")
def w46d(spark, d):
    """The same with the printed hashes."""
    return pages_pipeline(spark, d)


@query("w46b_gate_off", f"SELECT page_id FROM {VIEW_SQL} WHERE {score_sql(MAIN_SQL, 'fr')} > 0.05")
def w46b(spark, d):
    return pipeline.extract_stage(gate.gate_view(table(spark, d, "pages")), "fr", "off").select("page_id")


@query("w46c_detect_before_extract", f"SELECT page_id FROM {VIEW_SQL} WHERE {either_sql('fr')} AND {score_sql('html', 'fr')} > 0.05")
def w46c(spark, d):
    return pipeline.extract_stage(gate.gate_view(table(spark, d, "pages")), "fr", detect_before_extract=True).select("page_id")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Quality signals for every document, none removed."""
    a = quality.annotate(table(spark, d, "documents"), LATIN["en"])
    return a.select("doc_id", "lang", *[c for c in a.columns if c.startswith("q_")], F.array_join("reasons", ",").alias("reasons"))
