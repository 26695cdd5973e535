"""The registered queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from .decontaminate import WINDOW, op1_decontaminate
from .htmlcut import op2_html
from .lmscore import op4_lm_score
from .media import op6_media
from .mixing import op3_mixing
from .pii import op9_pii
from .shard import SHARDS, SLOTS, lookup_table, op10_shard
from .simhash import op7_simhash
from .tokencount import op5_tokens
from .toxicity import op8_toxicity

QUERIES = {f.__name__: f for f in (op1_decontaminate, op2_html, op3_mixing, op4_lm_score, op5_tokens, op6_media, op7_simhash, op8_toxicity, op9_pii, op10_shard)}

_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
_HITS = f"""WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, {_WORDS} AS w FROM documents),
  b AS (SELECT item_id::VARCHAR AS item, w, least(len(w), {WINDOW}) AS n FROM (SELECT item_id, {_WORDS} AS w FROM benchmark) WHERE len(w) > 0),
  p AS MATERIALIZED (SELECT DISTINCT item, n, array_to_string(w[i : i + n - 1], ' ') AS g FROM (SELECT item, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM b)),
  g AS (SELECT r, i, n, array_to_string(w[i : i + n - 1], ' ') AS g FROM (SELECT r, w, s.n, unnest(range(1, len(w) - s.n + 2)) AS i FROM d, (SELECT DISTINCT n FROM p) s WHERE len(w) >= s.n)),
  h AS MATERIALIZED (SELECT g.r, g.i, g.n, p.item FROM g JOIN p ON p.n = g.n AND p.g = g.g),
  k AS (SELECT r, count(DISTINCT j) AS n_hit FROM (SELECT r, unnest(range(i, i + n)) AS j FROM (SELECT DISTINCT r, i, n FROM h)) GROUP BY r),
  m AS (SELECT r, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT r, item FROM h WHERE item IS NOT NULL) GROUP BY r)"""


def _runs(values) -> str:
    """A SQL list of the table; DuckDB reads it from one string of two letters for each slot."""
    return "".join(chr(97 + v // 26) + chr(97 + v % 26) for v in values)


def _shard_sql() -> str:
    letters = _runs(lookup_table([f"shard-{k:05d}" for k in range(SHARDS)]).tolist())
    slot = f"(('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 15))::BIGINT % {SLOTS})"
    at = f"substr(t.letters, 2 * s.slot::INT + {{}}, 1)"  # noqa: F541
    return f"SELECT doc_id, slot, ((ascii({at.format(1)}) - 97) * 26 + ascii({at.format(2)}) - 97)::INT AS shard FROM (SELECT doc_id, {slot} AS slot FROM documents) s, (SELECT '{letters}' AS letters) t"


ORACLE_SQL: dict[str, str] = {
    "op1_decontaminate": f"""{_HITS} SELECT d.doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
  FROM d LEFT JOIN k ON k.r = d.r LEFT JOIN m ON m.r = d.r""",
    "op10_shard": _shard_sql(),
}
