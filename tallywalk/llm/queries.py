"""The queries of this subpackage, each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallywalk.llm import bpe, chat, decontaminate, html, jaccard, langid, quality, records, secrets, urls
from tallywalk.llm._frame import fresh_path


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan(table(spark, sf_dir, "documents"), ["doc_id"])
    count = lambda v: F.size(F.filter("spans", lambda s: s["verdict"] == v)).cast("bigint")
    return found.select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", secrets.spans_text(F.col("spans")).alias("spans"), count("live").alias("n_live"), count("example").alias("n_example"))


def op2_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.join(table(spark, sf_dir, "documents"))


# fixed values: the rules that the url query is given
URL_RULES = [urls.Rule.of(*r) for r in (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))]


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The urls that a rule judges are the labelled ones; the trees learn from a bounded sample of them and judge the rest."""
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    _, verdict = urls.longest_rule(urls.host_of(F.col("url")), urls.path_of(F.col("url")), URL_RULES)
    model = urls.fit(pages.withColumn("verdict", verdict))
    return urls.judge(pages, URL_RULES, model, keep=["page_id"]).withColumn("p_block", F.round("p_block", 6))


def op4_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digest(table(spark, sf_dir, "documents"), vocabulary(), ["doc_id"])


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.search(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", (F.size("found") > 0).alias("contaminated"), F.array_join(F.transform("found", lambda x: x["item_id"].cast("string")), ",").alias("item_ids"), F.coalesce(F.array_max(F.transform("found", lambda x: x["similarity"])), F.lit(0.0)).alias("similarity"))


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2
    model = langid.fit(docs.where(~held_out))
    return langid.predict(docs.select("doc_id", "text"), model).select("doc_id", held_out.alias("held_out"), "language.lang_pred", "language.score")


def op7_perspectives(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mask as text: run lengths, "+" where the loss counts."""
    mask = F.array_join(F.transform("mask", lambda x: F.concat(x["length"].cast("string"), F.when(x["target"], "+").otherwise("-"))), ",")
    return chat.rotate(table(spark, sf_dir, "conversations")).withColumn("mask", mask)


def op8_token_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = fresh_path(spark, "records")
    listing = records.write(table(spark, sf_dir, "documents"), folder, vocabulary(), end_id=2)
    return records.read(listing, folder, digests=True)


def op9_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(spark, sf_dir, "pages").select("page_id", "html")).select("page_id", "text")


def op10_quality_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    ledger = quality.apply_policy(quality.ledger(table(spark, sf_dir, "documents"), ["doc_id"]), "web-1")
    base = F.col("failed").bitwiseAND(F.lit(quality.mask("base-1")).cast("bigint")) != 0
    return ledger.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), "kept", "failed")


def queries() -> dict:
    return {f.__name__: f for f in (op1_secret_scan, op2_jaccard_join, op3_url_filter, op4_bpe_round_trip, op5_decontaminate, op6_language_id, op7_perspectives, op8_token_records, op9_html_text, op10_quality_ledger)}


OP2_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[\pL\pN_]+') AS ws FROM documents),
g AS MATERIALIZED (SELECT DISTINCT doc_id, array_to_string(ws[i : i + 4], ' ') AS gram FROM (SELECT doc_id, ws, unnest(range(1, greatest(2, len(ws) - 3))) AS i FROM w WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM g a JOIN g b ON a.gram = b.gram AND a.doc_id <> b.doc_id GROUP BY ALL),
links AS MATERIALIZED (SELECT a, b, CAST(k AS DOUBLE) / (x.n + y.n - k) AS similarity FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE CAST(k AS DOUBLE) / (x.n + y.n - k) >= 0.8 - 1e-12),
reach AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT reach.a, links.b FROM reach JOIN links ON links.a = reach.b)
SELECT d.doc_id, (SELECT min(b) FROM reach WHERE reach.a = d.doc_id) AS class_id, least(d.doc_id, coalesce((SELECT min(b) FROM links WHERE links.a = d.doc_id AND similarity = 1), d.doc_id)) AS copy_id,
    (SELECT count(*) FROM links WHERE links.a = d.doc_id) AS n_links FROM documents d
"""

OP5_SQL = r"""
WITH items AS (SELECT item_id, ws, len(ws) AS l FROM (SELECT item_id, regexp_extract_all(lower(text), '[\pL\pN_]+') AS ws FROM benchmark) WHERE len(ws) > 0),
ig AS MATERIALIZED (SELECT item_id, array_to_string(ws[i : i + 4], ' ') AS g, count(*) AS k FROM (SELECT item_id, ws, unnest(range(1, greatest(2, l - 3))) AS i FROM items) GROUP BY ALL),
w AS MATERIALIZED (SELECT g, 1 + ln((SELECT CAST(count(*) AS DOUBLE) FROM items) / count(DISTINCT item_id)) AS wt FROM ig GROUP BY g),
d AS MATERIALIZED (SELECT doc_id, ws, len(ws) AS n FROM (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[\pL\pN_]+') AS ws FROM documents) WHERE len(ws) > 0),
dg AS MATERIALIZED (SELECT doc_id, i, array_to_string(ws[i : i + 4], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, greatest(2, n - 3))) AS i FROM d)),
near AS (SELECT DISTINCT doc_id, item_id FROM dg JOIN ig USING (g)),
wins AS (SELECT doc_id, item_id, greatest(1, least(l, n) - 4) AS span, unnest(range(1, greatest(2, n - l + 2))) AS s FROM near JOIN d USING (doc_id) JOIN items USING (item_id)),
wg AS MATERIALIZED (SELECT wins.doc_id, item_id, s, g, count(*) AS k FROM wins JOIN dg ON dg.doc_id = wins.doc_id AND dg.i >= s AND dg.i < s + span GROUP BY ALL),
b AS (SELECT doc_id, item_id, s, sum(wt * least(ig.k, wg.k)) AS b FROM wg JOIN ig USING (item_id, g) JOIN w USING (g) GROUP BY ALL),
t AS (SELECT doc_id, item_id, s, sum(k * coalesce(wt, 1 + ln((SELECT CAST(count(*) AS DOUBLE) FROM items)))) AS t FROM wg LEFT JOIN w USING (g) GROUP BY ALL),
it AS (SELECT item_id, sum(k * wt) AS own FROM ig JOIN w USING (g) GROUP BY item_id),
hits AS (SELECT doc_id, item_id, max(b / (t + own - b)) AS similarity FROM b JOIN t USING (doc_id, item_id, s) JOIN it USING (item_id) GROUP BY ALL HAVING max(b / (t + own - b)) >= 0.8 - 1e-12)
SELECT doc_id, count(item_id) > 0 AS contaminated, coalesce(string_agg(CAST(item_id AS VARCHAR), ',' ORDER BY item_id), '') AS item_ids, coalesce(round(max(similarity), 6), 0.0) AS similarity FROM documents LEFT JOIN hits USING (doc_id) GROUP BY doc_id
"""

OP7_SQL = r"""
WITH r AS (SELECT DISTINCT conv_id, CAST(coalesce(floor(turn / 256), -1) AS BIGINT) AS chunk, turn, coalesce(role, 'unknown') AS who, regexp_replace(coalesce(text, ''), '<\|(im_start|im_end)\|>', '<| \1|>', 'g') AS said FROM conversations),
p AS (SELECT DISTINCT conv_id, who AS participant FROM r WHERE who <> 'system'),
t AS (SELECT conv_id, participant, chunk, turn, who, said, '<|im_start|>' || CASE WHEN who = participant THEN 'assistant' WHEN who = 'system' THEN who ELSE 'user name=' || who END || chr(10) AS head FROM r JOIN p USING (conv_id))
SELECT conv_id, participant, chunk, CAST(count(*) AS INTEGER) AS n_turns, string_agg(head || said || '<|im_end|>' || chr(10), '' ORDER BY turn, who, said) AS rendered,
    string_agg(CASE WHEN who = participant THEN length(head) || '-,' || (length(said) + 10) || '+,1-' ELSE (length(head) + length(said) + 11) || '-' END, ',' ORDER BY turn, who, said) AS mask
FROM t GROUP BY ALL
"""


def op10_sql() -> str:
    bits = " | ".join(f"(CASE WHEN {rule} THEN {quality.BIT[name]} ELSE 0 END)" for name, rule in quality.RULES)
    return rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
f AS (SELECT doc_id, ws[i : i + 2] AS win, i FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM d)),
again AS (SELECT doc_id, win FROM f GROUP BY ALL HAVING count(*) > 1),
rep AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM f JOIN again USING (doc_id, win), (SELECT unnest([0, 1, 2]) AS j) GROUP BY doc_id),
m AS (SELECT doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(ws, lambda w: length(w))), 0) AS BIGINT) AS word_chars,
    CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls,
    coalesce(rep.n, 0) AS n_repeat_words, length(regexp_replace(t, '[^\pL\p{{Nl}}\p{{No}}]', '', 'g')) AS n_letters, length(regexp_replace(t, '[^A-ZÀ-ÖØ-Þ]', '', 'g')) AS n_upper,
    len(list_filter(ws, lambda w: regexp_matches(w, '[#*$%&|<>!]{{2,}}$'))) AS n_marked_words, coalesce(list_max(list_transform(ws, lambda w: strlen(w))), 0) AS longest_word FROM d LEFT JOIN rep USING (doc_id)),
l AS (SELECT *, CAST(len(ls) AS BIGINT) AS n_lines, CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines FROM m),
b AS (SELECT *, CAST({bits} AS BIGINT) AS failed FROM l)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (failed & {quality.mask('base-1')}) <> 0 AS base_failed, (failed & {quality.mask('web-1')}) = 0 AS kept, failed FROM b
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_jaccard_join": OP2_SQL, "op5_decontaminate": OP5_SQL, "op7_perspectives": OP7_SQL, "op10_quality_ledger": op10_sql()}
