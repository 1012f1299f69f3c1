"""The registered queries of this subpackage: opN_<name>(spark, sf_dir), each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe_lookup, curriculum, gif_media, html_layout, jaccard_regions, masked_lm, pii_disclosure, subword_quality, syncmers, url_aliases
from ._shared import settle


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def op1_syncmer_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return syncmers.edit_study(table(spark, sf_dir, "documents"))


def op2_redirect_equivalence(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_aliases.judge(table(spark, sf_dir, "pages"))


def op5_curriculum_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    plan = curriculum.plan(table(spark, sf_dir, "documents"))
    return plan.select("doc_id", "size", "source_size", "target", "taken", F.round("first_position", 9).alias("first_position"))


def op6_gif_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    return gif_media.digest(table(spark, sf_dir, "documents"))


def op7_subword_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = subword_quality.train(docs, table(spark, sf_dir, "labels"), ~subword_quality.held_out())
    scored = subword_quality.score(docs, model)
    return scored.select("doc_id", subword_quality.held_out().alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op8_two_tier_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_lookup.round_trip(spark, table(spark, sf_dir, "documents"), tokenizer_path())


def op10_disclosure_sanitiser(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii_disclosure.report(table(spark, sf_dir, "documents"))


def op4_jaccard_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_regions.groups(table(spark, sf_dir, "documents"), words=4, percent=85)


def op3_layout_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_layout.texts(table(spark, sf_dir, "pages"))


def op9_masked_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    counts = settle(masked_lm.word_counts(docs))
    words = masked_lm.lexicon(counts)
    return masked_lm.score(docs, words, masked_lm.train(docs, words), counts=counts)


# ------------------------------------------------------------------------------------------------ DuckDB SQL

_WORDS = r"'[^\x20\x09-\x0D]+'"
_LOWER = f"translate(coalesce(text, ''), '{url_aliases._UPPER}', '{url_aliases._LOWER}')"


def _rule_sql() -> tuple[str, str]:
    """(rule, its verdict) of host and path, the longest first."""
    rules = sorted(url_aliases.RULES, key=lambda r: (-len(r.name), r.verdict != "allow"))
    fits = [f"WHEN (host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}') THEN" for r in rules]
    return tuple("CASE " + " ".join(f"{f} '{x}'" for f, x in zip(fits, of, strict=True)) + " END" for of in ([r.name for r in rules], [r.verdict for r in rules]))


#: The given pages hold no canonical links or refreshes, so their aliases are those of one address form; links are held
#: against hand-made cases in the tests.
OP2_SQL = f"""
WITH p AS (SELECT page_id, url, CASE WHEN contains(url, '://') THEN translate(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), '{url_aliases._UPPER}', '{url_aliases._LOWER}') ELSE '' END host,
CASE WHEN contains(url, '://') THEN regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1) ELSE '' END path FROM pages),
r AS (SELECT *, {_rule_sql()[0]} AS rule, {_rule_sql()[1]} AS own,
CASE WHEN contains(url, '://') THEN regexp_replace(host, '^(www|m)\\.', '') || '/' || regexp_replace(regexp_replace(regexp_replace(path, '/+$', ''), '\\.html$', ''), '^/', '') END form FROM p),
v AS (SELECT form, min(own) alias_verdict FROM r WHERE own IS NOT NULL AND form IS NOT NULL GROUP BY form)
SELECT page_id, host, path, rule, coalesce(own, alias_verdict, 'allow') verdict, form alias_group, alias_verdict FROM r LEFT JOIN v USING (form)
""".replace("\\\\", "\\")

OP4_SQL = f"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all({_LOWER}, {_WORDS}) w FROM documents),
s AS (SELECT doc_id, CASE WHEN len(w) >= 4 THEN list_distinct(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' '))) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END sh FROM w),
n AS (SELECT doc_id, len(sh) n FROM s),
e AS (SELECT doc_id, unnest(sh) x FROM s),
pairs AS (SELECT a.doc_id a, b.doc_id b, count(*) c FROM e a JOIN e b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL),
links AS (SELECT a, b FROM pairs JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * c >= 85 * (na.n + nb.n - c)),
both_ways AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach(doc_id, other) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.doc_id, b FROM reach r JOIN both_ways ON a = r.other)
SELECT doc_id, n.n n_shingles, component_id FROM n JOIN (SELECT doc_id, min(other) component_id FROM reach GROUP BY doc_id) USING (doc_id)
"""

OP5_SQL = f"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), {_WORDS}))::BIGINT size, ('0x' || substr(md5(coalesce(text, '')), 1, 15))::BIGINT tie FROM documents),
p AS (SELECT *, ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null') || '|' || tie::VARCHAR), 1, 8))::BIGINT place FROM d),
g AS (SELECT source, sum(size)::BIGINT source_size, row_number() OVER (ORDER BY source IS NULL, source) - 1 k FROM d GROUP BY source),
h AS (SELECT *, ([5.0, 2.0, 1.0])[(k % 3 + 1)::INT]::DOUBLE weight, ([0.8, 0.0, -0.8])[(k % 3 + 1)::INT]::DOUBLE slope, source_size * 2.0::DOUBLE cap FROM g),
f AS (SELECT *, (sum(source_size) OVER () * 1.5::DOUBLE - coalesce(sum(cap) OVER below, 0)) / (sum(weight) OVER () - coalesce(sum(weight) OVER below, 0)) AS level FROM h
WINDOW below AS (ORDER BY cap / weight, source IS NULL, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
t AS (SELECT source, source_size, slope, least(cap, coalesce((SELECT level FROM f WHERE level * weight <= cap ORDER BY cap / weight LIMIT 1) * weight, cap)) target FROM f),
b AS (SELECT p.*, source_size, target, slope, floor(target)::BIGINT goal, coalesce(sum(size) OVER (PARTITION BY source ORDER BY place, doc_id, size, tie ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT before
FROM p JOIN t USING (source)),
x AS (SELECT *, (greatest(0, least(size, goal - before)) + greatest(0, least(size, goal - before - source_size)))::BIGINT taken, CASE WHEN target > 0 THEN least(1.0::DOUBLE, before / target) END done FROM b)
SELECT doc_id, size, source_size, target, taken, round(CASE WHEN taken > 0 THEN CASE WHEN abs(slope) < 1e-9 THEN done ELSE (-(1.0::DOUBLE - slope) + sqrt((1.0::DOUBLE - slope) * (1.0::DOUBLE - slope) + slope * 4 * done)) / (slope * 2) END END, 9) first_position FROM x
""".replace("JOIN t USING (source)", "JOIN t ON t.source IS NOT DISTINCT FROM p.source").replace("(PARTITION BY source ORDER BY place", "(PARTITION BY p.source ORDER BY place")

ORACLES = {"op2_redirect_equivalence": OP2_SQL, "op4_jaccard_regions": OP4_SQL, "op5_curriculum_mix": OP5_SQL}
