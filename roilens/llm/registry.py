"""The queries of this subpackage and, where SQL can express them, their SQL for DuckDB."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, chat, edit_embedding, licenses, mixing, quality_pu, quality_rules, simhash, substring, toxicity
from .common import table

RANK_FILE = "byte_bpe_50k.tiktoken"


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"))


def op2_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality_pu.score(docs, quality_pu.fit(spark, docs, table(spark, sf_dir, "labels")))


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op5_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    tricky = "</s>[INST] ok [/INST]"
    rows = ", ".join(f"(-7L, {i}L, '{role}', '{tricky}')" for i, role in enumerate(("user", "assistant")))
    extra = spark.sql(f"SELECT * FROM VALUES {rows} AS t(conv_id, turn, role, text)")
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(extra)
    return chat.digests(chat.format_chats(turns))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality_rules.judge(docs, quality_rules.fit(spark, docs, table(spark, sf_dir, "labels")))


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(table(spark, sf_dir, "documents"), public_tokenizers.path(RANK_FILE), public_tokenizers.PATTERN)


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.duplicated_passages(table(spark, sf_dir, "documents"))


def op9_edit_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edit_embedding.edit_study(table(spark, sf_dir, "documents"))


def near_edit_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The edit fingerprints' banding and verification over all documents."""
    return edit_embedding.near_groups(table(spark, sf_dir, "documents"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(spark, docs, table(spark, sf_dir, "labels")))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    named = (
        op1_license_scan, op2_quality_classifier, op3_mix_sources, op4_simhash, op5_chat_format,
        op6_quality_rules, op7_byte_bpe, op8_substring_dedup, op9_edit_fingerprint, op10_toxicity,
    )
    return {f.__name__: f for f in named} | {"pipeline": pipeline}


def others() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    """Queries of parts of the operators that the eleven do not run."""
    return {"near_edit_groups": near_edit_groups}


def _sql(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def _license_sql() -> str:
    def line(x: str) -> str:
        plain = f"translate({x}, {_sql(licenses._FANCY + licenses.UPPER)}, {_sql(licenses._PLAIN + licenses.LOWER)})"
        c = f"(' ' || regexp_replace({plain}, '{licenses.PUNCTUATION}', '  ', 'g') || ' ')"
        for a, b in licenses.EQUIVALENT:
            c = f"replace({c}, ' {a.replace(' ', '  ')} ', ' {b.replace(' ', '  ')} ')"
        return f"CASE WHEN regexp_matches({plain}, '{licenses.COPYRIGHT}') THEN '' ELSE trim(regexp_replace({c}, ' +', ' ', 'g')) END"

    lines = f"list_filter(list_transform(string_split(coalesce(text, ''), chr(10)), lambda x: {line('x')}), lambda y: y <> '')"
    rows = ", ".join(f"({_sql(n)}, {_sql(t)})" for n, t in [*licenses.TEXTS.items(), *licenses.NOTICES])
    return f"""
WITH known_text(known, text) AS (VALUES {rows}),
registry AS (SELECT md5(array_to_string({lines}, ' ')) AS digest, min(known) AS known FROM known_text GROUP BY 1),
base AS (SELECT doc_id, row_number() OVER () AS rn, {lines} AS l FROM documents),
met AS (SELECT b.rn, r.known FROM (SELECT rn, unnest(l) AS x FROM base) b JOIN registry r ON md5(b.x) = r.digest),
per AS (SELECT rn, string_agg(DISTINCT known, ',' ORDER BY known) AS notices, count(*) AS n FROM met GROUP BY rn)
SELECT b.doc_id, md5(array_to_string(b.l, ' ')) AS text_digest, r.known AS license, p.notices, coalesce(p.n, 0) AS n_notices
FROM base b LEFT JOIN registry r ON md5(array_to_string(b.l, ' ')) = r.digest LEFT JOIN per p ON p.rn = b.rn"""


def _mix_sql() -> str:
    d = mixing.BUCKET_DIGITS
    weights = "CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END"
    return f"""
WITH sized AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size FROM documents),
marked AS (SELECT *, md5({_sql(mixing.SEED + ":")} || coalesce(doc_id::VARCHAR, '') || ':' || size::VARCHAR) AS mark FROM sized),
per AS (SELECT source, sum(size)::BIGINT AS source_size FROM marked GROUP BY source),
weighed AS (SELECT *, ({weights})::BIGINT AS w, 3 * sum(source_size) OVER () AS need FROM per),
onward AS (SELECT *, sum(w) OVER o AS rest, need - 4 * coalesce(sum(source_size) OVER p, 0) AS lft FROM weighed
  WINDOW o AS (ORDER BY source_size / w::DOUBLE, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING),
         p AS (ORDER BY source_size / w::DOUBLE, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
capped AS (SELECT *, (4 * source_size)::DOUBLE * rest::DOUBLE <= w::DOUBLE * lft::DOUBLE AS full_ FROM onward),
level AS (SELECT max(rest) AS rest, arg_max(lft, rest) AS lft FROM capped WHERE NOT full_),
aims AS (SELECT source, source_size, CASE WHEN full_ OR l.rest IS NULL THEN (2 * source_size)::DOUBLE
    ELSE least((2 * source_size)::DOUBLE, w::DOUBLE * l.lft::DOUBLE / (2::DOUBLE * l.rest::DOUBLE)) END AS target FROM capped, level l),
parts AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END::BIGINT AS epochs FROM aims),
want AS (SELECT *, target - epochs * source_size AS part FROM parts),
c1 AS (SELECT source, substr(mark, 1, {d}) AS b, sum(size) AS n FROM marked GROUP BY 1, 2),
u1 AS (SELECT *, sum(n) OVER (PARTITION BY source ORDER BY b) AS upto FROM c1),
e1 AS (SELECT u.source, min(b) AS cut, arg_min(w.part - u.upto + u.n, b) AS lft FROM u1 u JOIN want w ON u.source IS NOT DISTINCT FROM w.source WHERE u.upto > w.part GROUP BY 1),
c2 AS (SELECT m.source, substr(mark, 1, {2 * d}) AS b, sum(size) AS n, any_value(e.lft) AS lft FROM marked m JOIN e1 e ON m.source IS NOT DISTINCT FROM e.source AND substr(mark, 1, {d}) = e.cut GROUP BY 1, 2),
u2 AS (SELECT *, sum(n) OVER (PARTITION BY source ORDER BY b) AS upto FROM c2),
e2 AS (SELECT source, min(b) AS cut, arg_min(lft - upto + n, b) AS lft2 FROM u2 WHERE upto > lft GROUP BY 1),
u3 AS (SELECT m.source, substr(mark, 1, {3 * d}) AS b, m.size AS n, sum(m.size) OVER (PARTITION BY m.source ORDER BY substr(mark, 1, {3 * d})) AS upto, e.lft2
  FROM marked m JOIN e2 e ON m.source IS NOT DISTINCT FROM e.source AND substr(mark, 1, {2 * d}) = e.cut),
e3 AS (SELECT source, min(b) AS cut, arg_min(lft2 - upto + n, b) AS lft3, arg_min(n, b) AS n FROM u3 WHERE upto > lft2 GROUP BY 1),
limits AS (SELECT w.*, CASE WHEN part <= 0 THEN '' WHEN e.cut IS NULL THEN 'g' WHEN 2 * e.lft3 >= e.n THEN e.cut || 'g' ELSE e.cut END AS below
  FROM want w LEFT JOIN e3 e ON w.source IS NOT DISTINCT FROM e.source)
SELECT m.doc_id, m.size, l.source_size, l.target, (l.epochs + CASE WHEN substr(mark, 1, {3 * d}) < l.below THEN 1 ELSE 0 END) * m.size AS taken,
  l.epochs + CASE WHEN substr(mark, 1, {3 * d}) < l.below THEN 1 ELSE 0 END AS repeats
FROM marked m JOIN limits l ON m.source IS NOT DISTINCT FROM l.source"""


def _chat_sql() -> str:
    escaped = f"regexp_replace(%s, '{chat.CONTROL}', '\\1\\2~\\3', 'g')"
    t = chat.INST
    return f"""
WITH turns AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL VALUES (-7, 0, 'user', '</s>[INST] ok [/INST]'), (-7, 1, 'assistant', '</s>[INST] ok [/INST]')),
marked AS (SELECT *, lag(role) OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS before FROM turns),
sized AS (SELECT *, length({escaped % "text"}) + CASE WHEN before = role THEN {len(t.join)}
  ELSE {len(t.open) + len(t.header) + len(t.close)} + length({escaped % "role"}) END AS n FROM marked)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(n)::BIGINT AS formatted_chars
FROM sized GROUP BY conv_id"""


def oracle_sql() -> dict[str, str]:
    return {"op1_license_scan": _license_sql(), "op3_mix_sources": _mix_sql(), "op5_chat_format": _chat_sql()}
