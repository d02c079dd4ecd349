"""Phases 1, 2, 4 and 5 and the reports of a run."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.config import Config
from corpuskit.functions import metrics
from corpuskit.functions import text as T
from corpuskit.operators import clean, exact, neardup, quality
from corpuskit.plans import corpus as C
from corpuskit.plans import objective
from corpuskit.queries.registry import query, table, version
from corpuskit.session import staged
from corpuskit.sources import aggregate, pages_as_documents, with_roles

WS = r"[ \t\n\r\f\x0B]+"
#: Accented words, curly quotes and a dash: what damage shows on (the carrier of the damage fixtures).
TAIL = " café “naïve” – déjà vu"

RAW = f"""raw AS (SELECT doc_id, text, lang, source, CASE WHEN source = 'src0' THEN 20 ELSE CAST(substr(source, 4) AS INT) END AS rk,
 CASE WHEN source = 'src0' THEN 'seed' WHEN CAST(substr(source, 4) AS INT) <= 12 THEN 'A' ELSE 'B' END AS role,
 trim(regexp_replace(text, '{WS}', ' ', 'g')) AS spaced, sha256(trim(regexp_replace(lower(text), '{WS}', ' ', 'g'))) AS k FROM documents)"""
P1 = "p1 AS (SELECT * FROM raw QUALIFY row_number() OVER (PARTITION BY k ORDER BY rk, doc_id) = 1)"
P2 = """chars AS (SELECT *, string_split(spaced, '') AS cs FROM p1),
cl AS (SELECT * EXCLUDE (cs), array_to_string(list_filter(cs, lambda c, i: i <= 3 OR NOT (cs[i-1] = c AND cs[i-2] = c AND cs[i-3] = c)), '') AS clean FROM chars),
p2 AS (SELECT *, CAST(len(string_split(clean, ' ')) AS BIGINT) AS n_words FROM cl WHERE len(string_split(clean, ' ')) >= 50)"""
P3 = "p3 AS (SELECT * FROM p2 WHERE lang = 'en')"
SETS = """w AS (SELECT doc_id, string_split(clean, ' ') AS ws, length(clean) AS n_chars FROM p3),
sets AS (SELECT doc_id, n_chars, list_sort(list_distinct(list_transform(range(1, len(ws) - 1), lambda i: CAST('0x' || substr(md5(ws[i] || ' ' || ws[i+1] || ' ' || ws[i+2]), 1, 8) AS BIGINT) & 2147483647))) AS h FROM w),
hs AS (SELECT doc_id, len(h) AS n, unnest(h) AS x FROM sets)"""
BRUTE = """brute AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) / (any_value(a.n) + any_value(b.n) - count(*)) AS jaccard
 FROM hs a JOIN hs b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY 1, 2)"""
_FAMILY = neardup.hash_family()
SIG = "sig AS MATERIALIZED (SELECT doc_id, [" + ", ".join(f"list_min(list_transform(h, lambda x: (x * {a} + {c}) % {neardup.PRIME}))" for a, c in _FAMILY) + "] AS s FROM sets)"


def _bands(b: int, r: int) -> str:
    parts = ", ".join("concat_ws('-', " + ", ".join(f"s[{i * r + j + 1}]" for j in range(r)) + ")" for i in range(b))
    return f"bands{b} AS MATERIALIZED (SELECT doc_id, unnest(range({b})) AS band, unnest([{parts}]) AS key FROM sig)"


def _cands(b: int) -> str:
    return f"cands{b} AS (SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM bands{b} x JOIN bands{b} y ON x.band = y.band AND x.key = y.key AND x.doc_id < y.doc_id)"


VERIFIED = "verified AS (SELECT c.a, c.b, jaccard FROM cands16 c JOIN brute USING (a, b) WHERE jaccard >= 0.8)"
CLUSTERS = """both_ways AS (SELECT a, b FROM verified UNION SELECT b, a FROM verified),
reach AS (SELECT a AS doc_id, a AS other FROM both_ways UNION SELECT r.doc_id, e.b FROM reach r JOIN both_ways e ON r.other = e.a),
clusters AS (SELECT doc_id, min(other) AS component FROM reach GROUP BY 1)"""
P4 = """best AS (SELECT doc_id, row_number() OVER (PARTITION BY component ORDER BY length(clean) DESC, CAST(doc_id AS VARCHAR)) AS place FROM clusters JOIN p3 USING (doc_id)),
p4 AS (SELECT * FROM p3 WHERE doc_id NOT IN (SELECT doc_id FROM best WHERE place > 1))"""
GRAMS = """gr AS (SELECT doc_id, unnest(list_distinct(list_transform(range(1, length(clean) - 3), lambda i: substr(clean, i, 5)))) AS g FROM p4),
seed AS (SELECT DISTINCT g FROM gr WHERE doc_id IN (SELECT doc_id FROM p4 WHERE source = 'src0' AND n_words >= 200)),
scored AS (SELECT p4.doc_id, CAST(count(seed.g) AS BIGINT) AS hits, CAST(count(gr.g) AS BIGINT) AS total, CASE WHEN count(gr.g) > 0 THEN count(seed.g) / count(gr.g) ELSE 0 END AS coverage
 FROM p4 LEFT JOIN gr ON gr.doc_id = p4.doc_id LEFT JOIN seed ON seed.g = gr.g GROUP BY 1)"""
P5 = """cut AS (SELECT coverage AS least FROM (SELECT coverage, row_number() OVER (ORDER BY coverage) - 1 AS i, count(*) OVER () AS n FROM scored) WHERE i = n * 15 // 100),
p5 AS (SELECT p4.* FROM p4 JOIN scored USING (doc_id), cut WHERE coverage >= least)"""
UP3 = f"WITH {RAW}, {P1}, {P2}, {P3}"
UPSETS = f"{UP3}, {SETS}"
UPSIG = f"WITH RECURSIVE {RAW}, {P1}, {P2}, {P3}, {SETS}, {BRUTE}, {SIG}, {_bands(16, 4)}, {_cands(16)}, {VERIFIED}"
UP4 = f"{UPSIG}, {CLUSTERS}, {P4}"
UP5 = f"{UP4}, {GRAMS}, {P5}"

#: The profile model trained on the even documents that phase 1 leaves, and its answers for `asked(doc_id, t)`.
TRAIN = f"""prep AS (SELECT doc_id, lang, ' ' || trim(regexp_replace(lower(text), '{WS}', ' ', 'g')) || ' ' AS t FROM p1 WHERE doc_id % 2 = 0),
gm AS (SELECT lang AS label, n, unnest(list_transform(range(1, length(t) - n + 2), lambda i: substr(t, i, n))) AS gram FROM prep, (VALUES (1), (2), (3)) v(n)),
cnt AS MATERIALIZED (SELECT label, n, gram, count(*) AS c FROM gm GROUP BY ALL), voc AS (SELECT n, count(DISTINCT gram) AS v FROM cnt GROUP BY 1), tot AS (SELECT label, n, sum(c) AS t FROM cnt GROUP BY ALL),
prof AS (SELECT label, n, gram, ln((c + 0.5) / (t + 0.5 * v)) AS logp, ln(0.5 / (t + 0.5 * v)) AS unk FROM cnt JOIN tot USING (label, n) JOIN voc USING (n))"""
BAG = """bag AS MATERIALIZED (SELECT doc_id, n, gram, count(*) AS m FROM (SELECT doc_id, n, unnest(list_transform(range(1, length(t) - n + 2), lambda i: substr(t, i, n))) AS gram FROM asked, (VALUES (1), (2), (3)) v(n)) GROUP BY ALL)"""
SCORE = """unkn AS (SELECT DISTINCT label, n, unk FROM prof), sizes AS (SELECT doc_id, n, sum(m) AS size FROM bag GROUP BY ALL),
base AS (SELECT doc_id, label, sum(size * unk) AS base FROM sizes JOIN unkn USING (n) GROUP BY ALL),
gain AS (SELECT doc_id, label, sum(m * (logp - unk)) AS gain FROM bag JOIN prof USING (n, gram) GROUP BY ALL),
score AS (SELECT doc_id, label, base + coalesce(gain, 0) AS s FROM base LEFT JOIN gain USING (doc_id, label)),
pred AS MATERIALIZED (SELECT doc_id, label, 1 / sum(exp(s - top)) OVER (PARTITION BY doc_id) AS prob, row_number() OVER (PARTITION BY doc_id ORDER BY s DESC, label) AS place FROM (SELECT *, max(s) OVER (PARTITION BY doc_id) AS top FROM score))"""
IDENTIFIED = f"{TRAIN}, asked AS (SELECT doc_id, ' ' || trim(regexp_replace(lower(clean), '{WS}', ' ', 'g')) || ' ' AS t FROM p2), {BAG}, {SCORE}"
#: Phase 3 by that model instead of the labels that documents came with.
P3_MODEL = f"{IDENTIFIED}, p3 AS MATERIALIZED (SELECT p2.* FROM p2 JOIN pred USING (doc_id) WHERE place = 1 AND label = 'en' AND prob >= 0.5)"


def behind_model(sql: str) -> str:
    return sql.replace(P3, P3_MODEL)


_runs: dict[tuple, C.CorpusRun] = {}


def run_of(spark, sf_dir: str, identify=C.gold) -> C.CorpusRun:
    """One run for each input and session; its stages are written once and read by every report.

    Phases 4 and 5 are checked behind the labels the documents came with (gold), reports also behind the profile model
    (None); shingles are hashed by MD5, which SQL has too.
    """
    key = (*version(spark, sf_dir), identify)
    if key not in _runs:
        _runs[key] = C.CorpusRun(table(spark, sf_dir), identify=identify, base="md5")
    return _runs[key]


def _roles(spark, d) -> DataFrame:
    return with_roles(table(spark, d))


@query("agg_union", f"WITH {RAW} SELECT doc_id, source, CAST(rk - 1 AS INTEGER) AS source_rank, role, CAST(length(text) AS BIGINT) AS n FROM raw UNION ALL SELECT page_id, 'pages', 20, 'other', CAST(length(t) AS BIGINT) FROM (SELECT page_id, trim(regexp_replace(replace(replace(replace(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)\\b[^>]*>.*?</(script|style)\\s*>|<!--.*?-->', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&#39;', ''''), '&apos;', ''''), '&nbsp;', chr(160)), '&copy;', '©'), '&middot;', '·'), '&amp;', '&'), '{WS}', ' ', 'g')) AS t FROM pages)")
def agg_union(spark, d):
    rows = aggregate([table(spark, d).select("doc_id", "source", "text"), pages_as_documents(table(spark, d, "pages"))])
    return rows.select("doc_id", "source", "source_rank", "role", F.char_length("text").cast("long").alias("n"))


@query("inv_sources", "SELECT source, count(*) AS n_docs, CAST(sum(len(list_filter(regexp_split_to_array(text, '" + WS + "'), lambda w: w <> ''))) AS BIGINT) AS n_tokens, CAST(sum(strlen(text)) AS BIGINT) AS n_bytes FROM documents GROUP BY ROLLUP (source)")
def inv_sources(spark, d):
    return C.inventory(table(spark, d))


@query("page_text", f"SELECT page_id, trim(regexp_replace(replace(replace(replace(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)\\b[^>]*>.*?</(script|style)\\s*>|<!--.*?-->', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&#39;', ''''), '&apos;', ''''), '&nbsp;', chr(160)), '&copy;', '©'), '&middot;', '·'), '&amp;', '&'), '{WS}', ' ', 'g')) AS text FROM pages")
def page_text(spark, d):
    return pages_as_documents(table(spark, d, "pages")).select(F.col("doc_id").alias("page_id"), "text")


@query("p1_key", f"WITH {RAW} SELECT doc_id, k AS content_key FROM raw")
def p1_key(spark, d):
    return exact.keyed(table(spark, d)).select("doc_id", "content_key")


@query("p1_exact_dedup", f"WITH {RAW}, {P1} SELECT doc_id, source FROM p1")
def p1_exact_dedup(spark, d):
    return exact.drop_exact(_roles(spark, d)).select("doc_id", "source")


@query("p1_exact_window", f"WITH {RAW}, {P1} SELECT doc_id, source FROM p1")
def p1_exact_window(spark, d):
    return exact.drop_exact_window(_roles(spark, d)).select("doc_id", "source")


@query("p1_exact_raw", f"WITH {RAW} SELECT doc_id, source FROM raw QUALIFY row_number() OVER (PARTITION BY sha256(text) ORDER BY rk, doc_id) = 1")
def p1_exact_raw(spark, d):
    return exact.drop_exact(_roles(spark, d), "raw").select("doc_id", "source")


@query("p1_incremental", f"WITH {RAW} SELECT doc_id FROM raw WHERE doc_id % 2 = 1 AND k NOT IN (SELECT k FROM raw WHERE doc_id % 2 = 0) QUALIFY row_number() OVER (PARTITION BY k ORDER BY rk, doc_id) = 1")
def p1_incremental(spark, d):
    docs = _roles(spark, d)
    seen = exact.keyed(docs.filter("doc_id % 2 = 0")).select("content_key").distinct()
    return exact.drop_exact_incremental(docs.filter("doc_id % 2 = 1"), seen).select("doc_id")


@query("p1_groups", f"WITH {RAW} SELECT k AS content_key, count(*) AS copies, arg_min(doc_id, (rk, doc_id)) AS first_id FROM raw GROUP BY 1 HAVING count(*) > 1")
def p1_groups(spark, d):
    return exact.groups(_roles(spark, d))


@query("p1_rate_attributed", f"WITH {RAW}, {P1} SELECT r.source, count(*) AS n_docs, CAST(sum(CASE WHEN p1.doc_id IS NULL THEN 1 ELSE 0 END) AS BIGINT) AS n_removed, round(sum(CASE WHEN p1.doc_id IS NULL THEN 1 ELSE 0 END) / count(*), 6) AS rate FROM raw r LEFT JOIN p1 USING (doc_id) GROUP BY 1")
def p1_rate_attributed(spark, d):
    return exact.rate_attributed(_roles(spark, d))


@query("p1_rate_within", f"WITH {RAW} SELECT source, count(*) AS n_docs, count(DISTINCT k) AS n_keys, round(1 - count(DISTINCT k) / count(*), 6) AS rate FROM raw GROUP BY 1")
def p1_rate_within(spark, d):
    return exact.rate_within(_roles(spark, d))


@query("p1_overlap", f"WITH {RAW}, s AS (SELECT DISTINCT k, source FROM raw) SELECT a.source AS source_a, b.source AS source_b, count(*) AS n_keys FROM s a JOIN s b ON a.k = b.k AND a.source < b.source GROUP BY 1, 2")
def p1_overlap(spark, d):
    return exact.overlap(_roles(spark, d))


@query("p1_approx_rate")
def p1_approx_rate(spark, d):
    return exact.approx_rate(_roles(spark, d))


def _damaged(text, charset: str):
    """text with a carrier tail, its UTF-8 bytes read as a one-byte charset; of every third document twice, of every
    third not at all: those come back as they are."""
    carrier = F.concat(text, F.lit(TAIL))
    if charset == "latin":
        once = lambda c: F.decode(F.encode(c, "UTF-8"), "ISO-8859-1")
        return F.when(F.col("doc_id") % 3 == 0, once(once(carrier))).when(F.col("doc_id") % 3 == 1, once(carrier)).otherwise(carrier)
    wide = F.translate(F.decode(F.encode(carrier, "UTF-8"), "ISO-8859-1"), T._PLACES_1252, T._PUNCTUATION_1252)
    return F.when(F.col("doc_id") % 3 == 2, carrier).otherwise(wide)


_CARRIERS = "SELECT doc_id, md5(text || '" + TAIL + "') AS repaired FROM documents"


def _broken(docs: DataFrame, damage) -> DataFrame:
    return T.computed(docs.select("doc_id", "text"), broken=damage)


@query("p2_repair", _CARRIERS)
def p2_repair(spark, d):
    return _broken(table(spark, d), _damaged(F.col("text"), "latin")).select("doc_id", F.md5(T.repair_mojibake(F.col("broken"))).alias("repaired"))


@query("p2_repair_1252", _CARRIERS)
def p2_repair_1252(spark, d):
    return _broken(table(spark, d), _damaged(F.col("text"), "1252")).select("doc_id", F.md5(T.repair_mojibake(F.col("broken"))).alias("repaired"))


@query("p2_repair_mixed", "SELECT doc_id, md5(text || '" + TAIL + " €“" + TAIL + "') AS repaired FROM documents")
def p2_repair_mixed(spark, d):
    rows = _broken(table(spark, d), F.concat("text", F.lit(TAIL + " €“"), _damaged(F.lit(""), "latin")))
    return T.repair_mixed(rows, "broken", "whole").select("doc_id", F.md5("whole").alias("repaired"))


@query("p2_fix_entities", "SELECT page_id, md5(replace(replace(replace(replace(replace(replace(replace(replace(replace(html, '&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&#39;', ''''), '&apos;', ''''), '&nbsp;', chr(160)), '&copy;', '©'), '&middot;', '·'), '&amp;', '&')) AS fixed FROM pages")
def p2_fix_entities(spark, d):
    return table(spark, d, "pages").select("page_id", F.md5(T.decode_entities(F.col("html"))).alias("fixed"))


@query("p2_fix_other", "SELECT doc_id, md5(replace(text, chr(10), chr(10) || 'it''s \"ffi\" ABC ')) AS fixed FROM documents")
def p2_fix_other(spark, d):
    dirty = F.replace("text", F.lit("\n"), F.lit("\x07﻿\r\nit’s\x1b[31m “ﬃ”\x1b[0m ＡＢＣ　"))
    return table(spark, d).select("doc_id", F.md5(T.fix_text(dirty, ("controls", "lines", "quotes", "ligatures", "width"))).alias("fixed"))


_DECOMPOSED = (("é", "é"), ("è", "è"), ("ê", "ê"), ("ü", "ü"), ("ö", "ö"), ("ä", "ä"), ("ñ", "ñ"), ("ó", "ó"), ("í", "í"), ("ç", "ç"))


@query("p2_nfc", "SELECT doc_id, md5(nfc_normalize(" + reduce(lambda s, x: f"replace({s}, '{x[0]}', '{x[1]}')", _DECOMPOSED, "text") + ")) AS composed FROM documents")
def p2_nfc(spark, d):
    apart = reduce(lambda c, x: F.replace(c, F.lit(x[0]), F.lit(x[1])), _DECOMPOSED, F.col("text"))
    return table(spark, d).select("doc_id", F.md5(T.nfc(apart)).alias("composed"))


@query("p2_ws", f"SELECT doc_id, md5(trim(regexp_replace(text, '{WS}', ' ', 'g'))) AS spaced FROM documents")
def p2_ws(spark, d):
    return table(spark, d).select("doc_id", F.md5(T.collapse_ws(F.col("text"))).alias("spaced"))


@query("p2_runs", "WITH c AS (SELECT doc_id, string_split(text, '') AS cs FROM documents) SELECT doc_id, md5(array_to_string(list_filter(cs, lambda c, i: i <= 3 OR NOT (cs[i-1] = c AND cs[i-2] = c AND cs[i-3] = c)), '')) AS shortened FROM c")
def p2_runs(spark, d):
    return table(spark, d).select("doc_id", F.md5(T.collapse_runs(F.col("text"))).alias("shortened"))


@query("p2_clean", f"WITH {RAW}, {P1}, {P2} SELECT doc_id, md5(clean) AS cleaned FROM cl")
def p2_clean(spark, d):
    return clean.normalize(run_of(spark, d).unique).select("doc_id", F.md5("clean").alias("cleaned"))


@query("p2_minwords", f"WITH {RAW}, {P1}, {P2} SELECT doc_id, n_words FROM p2")
def p2_minwords(spark, d):
    return run_of(spark, d).cleaned.select("doc_id", "n_words")


@query("p2_repair_rate", f"WITH {RAW}, {P1}, {P2}, f AS (SELECT role, CASE WHEN doc_id % 3 < 2 THEN 1 ELSE 0 END AS hit FROM (SELECT role, doc_id, 5 + len(string_split(clean, ' ')) AS n FROM cl) WHERE n >= 50) SELECT role, count(*) AS n_survivors, CAST(sum(hit) AS BIGINT) AS n_repaired, round(sum(hit) / count(*), 6) AS rate_among_survivors FROM f GROUP BY ROLLUP (role)")
def p2_repair_rate(spark, d):
    broken = T.computed(run_of(spark, d).unique.withColumnRenamed("text", "whole"), text=_damaged(F.col("whole"), "latin"))
    return clean.repair_rate(clean.min_words(clean.normalize(broken)), "role")


@query("p2_drop_reasons", f"WITH {RAW}, {P1}, {P2} SELECT CASE WHEN len(string_split(clean, ' ')) < 50 THEN 'short' ELSE 'kept' END AS reason, count(*) AS n_docs FROM cl GROUP BY 1")
def p2_drop_reasons(spark, d):
    return clean.drop_reasons(clean.normalize(run_of(spark, d).unique))


@query("p4_shingles", f"{UPSETS} SELECT doc_id, CAST(len(h) AS BIGINT) AS n_shingles, CAST(list_sum(h) AS BIGINT) AS checksum FROM sets")
def p4_shingles(spark, d):
    sets = neardup.hashed(neardup.shingles(run_of(spark, d).p3))
    return sets.select("doc_id", F.size("hashes").cast("long").alias("n_shingles"), F.aggregate("hashes", F.lit(0).cast("long"), lambda s, x: s + x).alias("checksum"))


@query("p4_bruteforce", f"{UPSETS}, {BRUTE} SELECT a, b, round(jaccard, 6) AS jaccard FROM brute")
def p4_bruteforce(spark, d):
    return neardup.brute_force(run_of(spark, d).near.sets).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


@query("p4_jaccard", f"{UPSETS}, {BRUTE} SELECT a, b, round(jaccard, 6) AS jaccard FROM brute WHERE jaccard >= 0.5")
def p4_jaccard(spark, d):
    return neardup.brute_force(run_of(spark, d).near.sets, 0.5).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


@query("p4_prefix_join", f"{UPSETS}, {BRUTE} SELECT a, b, round(jaccard, 6) AS jaccard FROM brute WHERE jaccard >= 0.8")
def p4_prefix_join(spark, d):
    return neardup.prefix_join(run_of(spark, d).near.sets).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


@query("p4_signature", f"{UPSETS}, {SIG} SELECT doc_id, md5(array_to_string(s, '-')) AS signature FROM sig")
def p4_signature(spark, d):
    return neardup.signatures(run_of(spark, d).near.sets).select("doc_id", F.md5(F.concat_ws("-", "signature")).alias("signature"))


@query("p4_signature_native", f"{UPSETS}, {SIG} SELECT doc_id, md5(array_to_string(s, '-')) AS signature FROM sig")
def p4_signature_native(spark, d):
    return neardup.signatures_native(run_of(spark, d).near.sets).select("doc_id", F.md5(F.concat_ws("-", "signature")).alias("signature"))


@query("p4_bands", f"{UPSETS}, {SIG}, {_bands(16, 4)} SELECT doc_id, CAST(band AS INTEGER) AS band, key FROM bands16")
def p4_bands(spark, d):
    return neardup.bands(neardup.signatures(run_of(spark, d).near.sets))


@query("p4_candidates", f"{UPSETS}, {SIG}, {_bands(16, 4)}, {_cands(16)} SELECT a, b FROM cands16")
def p4_candidates(spark, d):
    return neardup.candidates(neardup.bands(neardup.signatures(run_of(spark, d).near.sets)))


@query("p4_star_candidates", f"{UPSETS}, {SIG}, {_bands(16, 4)}, m AS (SELECT *, min(doc_id) OVER (PARTITION BY band, key) AS a FROM bands16) SELECT DISTINCT a, doc_id AS b FROM m WHERE a < doc_id")
def p4_star_candidates(spark, d):
    return neardup.star_candidates(neardup.bands(neardup.signatures(run_of(spark, d).near.sets)))


@query("p4_bucket_report", f"{UPSETS}, {SIG}, {_bands(16, 4)}, m AS (SELECT band, count(*) AS m FROM bands16 GROUP BY band, key HAVING count(*) > 2) SELECT CAST(band AS INTEGER) AS band, count(*) AS buckets, CAST(sum(m) AS BIGINT) AS docs, CAST(sum(m * (m - 1) // 2 - (m - 1)) AS BIGINT) AS pairs_skipped FROM m GROUP BY 1")
def p4_bucket_report(spark, d):
    return neardup.bucket_report(neardup.bands(neardup.signatures(run_of(spark, d).near.sets)), 2)


@query("p4_estimate", f"{UPSETS}, {SIG}, {_bands(16, 4)}, {_cands(16)} SELECT c.a, c.b, round(len(list_filter(range(1, 65), lambda i: x.s[i] = y.s[i])) / 64, 6) AS estimate FROM cands16 c JOIN sig x ON x.doc_id = c.a JOIN sig y ON y.doc_id = c.b")
def p4_estimate(spark, d):
    sigs = neardup.signatures(run_of(spark, d).near.sets)
    pairs = neardup.candidates(neardup.bands(sigs))
    both = pairs.join(sigs.toDF("a", "sa"), "a").join(sigs.toDF("b", "sb"), "b")
    return both.select("a", "b", F.round(neardup.estimate(F.col("sa"), F.col("sb")), 6).alias("estimate"))


@query("p4_estimate_only", f"{UPSETS}, {SIG}, {_bands(16, 4)}, {_cands(16)} SELECT c.a, c.b FROM cands16 c JOIN sig x ON x.doc_id = c.a JOIN sig y ON y.doc_id = c.b WHERE len(list_filter(range(1, 65), lambda i: x.s[i] = y.s[i])) / 64 >= 0.8")
def p4_estimate_only(spark, d):
    return p4_estimate(spark, d).filter("estimate >= 0.8").select("a", "b")


@query("p4_s_curve", "SELECT bands, rows, i / 20 AS s, round(1 - pow(1 - pow(i / 20, rows), bands), 6) AS probability FROM (VALUES (16, 4), (8, 8), (32, 2)) t(bands, rows), range(21) r(i)")
def p4_s_curve(spark, d):
    return neardup.s_curve_table(spark)


_SWEEP = " UNION ALL ".join(
    f"SELECT {b} AS bands, {r} AS rows, count(*) AS candidates, count(jaccard) FILTER (jaccard >= 0.8) AS true_pairs, round(count(jaccard) FILTER (jaccard >= 0.8) / count(*), 6) AS precision, round(count(jaccard) FILTER (jaccard >= 0.8) / (SELECT count(*) FROM brute WHERE jaccard >= 0.8), 6) AS recall FROM cands{b} LEFT JOIN brute USING (a, b)"
    for b, r in ((16, 4), (8, 8), (32, 2))
)


@query("p4_sweep", f"{UPSETS}, {BRUTE}, {SIG}, {_bands(16, 4)}, {_cands(16)}, {_bands(8, 8)}, {_cands(8)}, {_bands(32, 2)}, {_cands(32)} {_SWEEP}")
def p4_sweep(spark, d):
    return neardup.sweep(run_of(spark, d).near.sets)


@query("p4_capture", f"{UPSETS}, {BRUTE}, {SIG}, {_bands(16, 4)}, {_cands(16)} SELECT CAST(least(floor(jaccard * 10), 9) AS BIGINT) AS bin, count(*) AS n_pairs, count(c.a) AS n_captured FROM brute LEFT JOIN cands16 c USING (a, b) GROUP BY 1")
def p4_capture(spark, d):
    """Empirical capture of (16, 4) by similarity."""
    sets = run_of(spark, d).near.sets
    found = neardup.verify(neardup.candidates(neardup.bands(neardup.signatures(sets))), sets, 0.0).filter("jaccard > 0")
    captured = found.groupBy(F.least(F.floor(F.col("jaccard") * 10), F.lit(9)).cast("long").alias("bin")).agg(F.count("*").alias("n_captured"))
    return neardup.similarity_histogram(sets).join(captured, "bin", "left").select("bin", "n_pairs", F.coalesce("n_captured", F.lit(0)).cast("long").alias("n_captured"))


@query("p4_verified", f"{UPSIG} SELECT a, b, round(jaccard, 6) AS jaccard FROM verified")
def p4_verified(spark, d):
    """Pairs between all documents: those of representatives, and members of one class with similarity 1."""
    near = run_of(spark, d).near
    pairs = neardup.candidates(neardup.bands(neardup.signatures(near.sets)))
    return neardup.verify(pairs, near.sets).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


@query("p4_components", f"{UPSIG}, {CLUSTERS} SELECT doc_id, component FROM clusters")
def p4_components(spark, d):
    return run_of(spark, d).clusters


@query("p4_survivors", f"{UP4} SELECT doc_id FROM p4")
def p4_survivors(spark, d):
    return run_of(spark, d).p4.select("doc_id")


@query("p4_cluster_stats", f"{UPSIG}, {CLUSTERS} SELECT count(DISTINCT component) AS n_clusters, count(*) AS n_covered, count(*) - count(DISTINCT component) AS n_removed FROM clusters")
def p4_cluster_stats(spark, d):
    return neardup.cluster_stats(run_of(spark, d).clusters)


@query("p4_cluster_sizes", f"{UPSIG}, {CLUSTERS}, s AS (SELECT component, count(*) AS size FROM clusters GROUP BY 1) SELECT size, count(*) AS n_clusters FROM s GROUP BY 1")
def p4_cluster_sizes(spark, d):
    return neardup.cluster_sizes(run_of(spark, d).clusters)


@query("p4_recall", f"{UPSIG}, t AS (SELECT a, b FROM brute WHERE jaccard >= 0.8), c AS (SELECT count(v.a) FILTER (t.a IS NOT NULL) AS tp, count(v.a) FILTER (t.a IS NULL) AS fp, count(t.a) FILTER (v.a IS NULL) AS fn FROM verified v FULL JOIN t USING (a, b)) SELECT tp, fp, fn, round(tp / (tp + fp), 6) AS precision, round(tp / (tp + fn), 6) AS recall, round(2 * tp / (2 * tp + fp + fn), 6) AS f1 FROM c")
def p4_recall(spark, d):
    return metrics.pair_prf(p4_verified(spark, d), neardup.brute_force(run_of(spark, d).near.sets, 0.8))


@query("p4_mllib")
def p4_mllib(spark, d):
    return neardup.mllib_candidates(run_of(spark, d).near.distinct)


_DAMPED = """v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings
 UNION ALL SELECT vec_id + 1000000000, list_transform(embedding, lambda x, i: CASE WHEN i % 8 = 0 THEN 0.0 ELSE CAST(x AS DOUBLE) END) FROM embeddings)"""


@query("p4_vectors", f"WITH {_DAMPED} SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(a.e, b.e) >= 0.9")
def p4_vectors(spark, d):
    """Near vectors among the given ones and copies of them without every eighth component: the given ones have none."""
    given = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("embedding"))
    damped = F.transform("embedding", lambda x, i: F.when(i % 8 == 7, 0.0).otherwise(x))
    copies = given.select((F.col("vec_id") + 1_000_000_000).alias("vec_id"), damped.alias("embedding"))
    return neardup.vector_pairs(given.unionByName(copies), 0.9).select("a", "b")


@query("p5_seed", f"{UP4} SELECT doc_id, n_words FROM p4 WHERE source = 'src0' AND n_words >= 200")
def p5_seed(spark, d):
    return run_of(spark, d).seed.select("doc_id", "n_words")


@query("p5_seed_stats", f"{UP4}, {GRAMS} SELECT (SELECT count(*) FROM p4 WHERE source = 'src0' AND n_words >= 200) AS n_docs, count(*) AS n_grams FROM seed")
def p5_seed_stats(spark, d):
    run = run_of(spark, d)
    return run.seed.agg(F.count("*").alias("n_docs")).crossJoin(quality.hashed_seed(run.seed).agg(F.count("*").alias("n_grams")))


_COVERAGE = f"{UP4}, {GRAMS} SELECT doc_id, hits, total, round(coverage, 9) AS coverage FROM scored"


@query("p5_coverage", _COVERAGE)
def p5_coverage(spark, d):
    return run_of(spark, d).scored.withColumn("coverage", F.round("coverage", 9))


@query("p5_coverage_joined", _COVERAGE)
def p5_coverage_joined(spark, d):
    run = run_of(spark, d)
    return quality.coverage_joined(run.p4, quality.seed_grams(run.seed)).withColumn("coverage", F.round("coverage", 9))


@query("p5_filter", f"{UP5} SELECT doc_id FROM p5")
def p5_filter(spark, d):
    return run_of(spark, d).p5_ids


@query("p5_filter_interp", f"{UP4}, {GRAMS} SELECT doc_id FROM scored WHERE coverage >= (SELECT quantile_cont(coverage, 0.15) FROM scored)")
def p5_filter_interp(spark, d):
    return quality.drop_bottom(run_of(spark, d).scored, 15, "interpolated").select("doc_id")


@query("p5_filter_approx")
def p5_filter_approx(spark, d):
    return quality.drop_bottom(run_of(spark, d).scored, 15, "approx").select("doc_id")


@query("p5_filter_abs", f"{UP4}, {GRAMS} SELECT doc_id FROM scored WHERE coverage >= 0.9029")
def p5_filter_abs(spark, d):
    return quality.drop_below(run_of(spark, d).scored, 0.9029).select("doc_id")


@query("p5_filter_by_source", f"{UP4}, {GRAMS}, s AS (SELECT doc_id, role, coverage, row_number() OVER (PARTITION BY role ORDER BY coverage) - 1 AS i, count(*) OVER (PARTITION BY role) AS n FROM scored JOIN p4 USING (doc_id)), c AS (SELECT role, coverage AS least FROM s WHERE i = n * 15 // 100) SELECT doc_id, role FROM s JOIN c USING (role) WHERE coverage >= least")
def p5_filter_by_source(spark, d):
    run = run_of(spark, d)
    return quality.drop_bottom_by(run.scored.join(run.p4.select("doc_id", "role"), "doc_id"), "role").select("doc_id", "role")


@query("p5_hist", f"{UP4}, {GRAMS} SELECT CAST(least(floor(coverage * 20), 19) AS BIGINT) AS bin, count(*) AS n_docs FROM scored GROUP BY 1")
def p5_hist(spark, d):
    return quality.histogram(run_of(spark, d).scored)


@query("p5_drop_by_source", f"{UP5} SELECT p4.role, count(*) AS n_docs, count(*) - count(p5.doc_id) AS n_dropped, round((count(*) - count(p5.doc_id)) / count(*), 6) AS drop_rate FROM p4 LEFT JOIN p5 USING (doc_id) GROUP BY 1")
def p5_drop_by_source(spark, d):
    run = run_of(spark, d)
    return C.drop_by_source(run.p4, run.p5_ids)


@query("p5_seed_labels", f"{UP4}, gr AS (SELECT doc_id, unnest(list_distinct(list_transform(range(1, length(clean) - 3), lambda i: substr(clean, i, 5)))) AS g FROM p4), seed AS (SELECT DISTINCT g FROM gr WHERE doc_id IN (SELECT doc_id FROM p4 JOIN labels USING (doc_id) WHERE quality = 1 AND n_words >= 200)) SELECT doc_id, CAST(count(seed.g) AS BIGINT) AS hits, CAST(count(*) AS BIGINT) AS total FROM gr LEFT JOIN seed USING (g) GROUP BY 1")
def p5_seed_labels(spark, d):
    run = run_of(spark, d)
    return quality.coverage(run.p4, quality.labelled_seed(run.p4, table(spark, d, "labels"))).select("doc_id", "hits", "total")


@query("p5_auc", f"{UP4}, {GRAMS}, s AS (SELECT coverage, quality FROM scored JOIN labels USING (doc_id)), p AS (SELECT sum(CASE WHEN a.coverage > b.coverage THEN 1 WHEN a.coverage = b.coverage THEN 0.5 ELSE 0 END) AS won FROM s a, s b WHERE a.quality = 1 AND b.quality = 0) SELECT CAST(sum(quality) AS BIGINT) AS n_pos, CAST(sum(1 - quality) AS BIGINT) AS n_neg, round(CAST((SELECT won FROM p) AS DOUBLE) / (sum(quality) * sum(1 - quality)), 6) AS auc FROM s")
def p5_auc(spark, d):
    return quality.auc(run_of(spark, d).scored, table(spark, d, "labels"))


@query("p5_drop_quality", f"{UP5}, r AS (SELECT quality = 0 AS poor, p5.doc_id IS NULL AS gone FROM scored JOIN labels USING (doc_id) LEFT JOIN p5 USING (doc_id)), c AS (SELECT count(*) AS n_labelled, count(*) FILTER (poor) AS n_poor, count(*) FILTER (gone) AS n_dropped, count(*) FILTER (poor AND gone) AS n_hit FROM r) SELECT *, round(CASE WHEN n_dropped > 0 THEN n_hit / n_dropped ELSE 0 END, 6) AS precision, round(CASE WHEN n_poor > 0 THEN n_hit / n_poor ELSE 0 END, 6) AS recall FROM c")
def p5_drop_quality(spark, d):
    """How well what phase 5 drops agrees with the documents rated poor."""
    run = run_of(spark, d)
    return quality.evaluate_drop(run.scored, run.p5_ids, table(spark, d, "labels"))


@query("p5_perplexity")
def p5_perplexity(spark, d):
    """The same measures with the character model's score instead of coverage."""
    run = run_of(spark, d)
    scored = staged(quality.perplexity_score(run.p4, run.seed), "perplexity")
    kept = quality.drop_bottom(scored, run.config.drop_percent)
    return quality.evaluate_drop(scored, kept, table(spark, d, "labels")).crossJoin(quality.auc(scored, table(spark, d, "labels")).select("auc"))


@query("p5_classifier")
def p5_classifier(spark, d):
    run = run_of(spark, d)
    even = run.p4.filter("doc_id % 2 = 0")
    scores = quality.train_classifier(even, table(spark, d, "labels"), 1 << 14)(run.p4.filter("doc_id % 2 = 1"))
    return quality.auc(scores, table(spark, d, "labels"), "probability")


_STAGED = "SELECT 'raw' AS stage, role, source, doc_id, CAST(len(list_filter(regexp_split_to_array(text, '" + WS + "'), lambda w: w <> '')) AS BIGINT) AS n_words FROM raw UNION ALL SELECT 'p1', role, source, doc_id, CAST(len(list_filter(regexp_split_to_array(text, '" + WS + "'), lambda w: w <> '')) AS BIGINT) FROM p1 " + " ".join(f"UNION ALL SELECT '{p}', role, source, doc_id, n_words FROM {p}" for p in ("p2", "p3", "p4", "p5"))
_ORDER = "list_position(['raw', 'p1', 'p2', 'p3', 'p4', 'p5'], stage)"


def _retention_sql(by: str) -> str:
    part = f"PARTITION BY {by} " if by else ""
    pre = f"{by}, " if by else ""
    return f"{UP5}, st AS ({_STAGED}), c AS (SELECT {pre}stage, count(*) AS n_docs, CAST(sum(n_words) AS BIGINT) AS n_words FROM st GROUP BY ALL) SELECT {pre}stage, n_docs, n_words, round(100 * n_docs / first_value(n_docs) OVER w, 4) AS cumulative_pct, round(100 * (1 - n_docs / lag(n_docs) OVER w), 4) AS step_drop_pct FROM c WINDOW w AS ({part}ORDER BY {_ORDER})"


@query("retention", behind_model(_retention_sql("")))
def retention(spark, d):
    return C.retention(run_of(spark, d, None).stage_rows())


@query("retention_by_source", behind_model(_retention_sql("role")))
def retention_by_source(spark, d):
    return C.retention_by_source(run_of(spark, d, None).stage_rows())


@query("retention_gold", _retention_sql(""))
def retention_gold(spark, d):
    """The same behind the labels that documents came with."""
    return C.retention(run_of(spark, d).stage_rows())


@query("composition", behind_model(f"{UP5} SELECT role, count(*) AS kept_docs, round(count(*) / (SELECT count(*) FROM p5), 6) AS fraction FROM p5 GROUP BY 1"))
def composition(spark, d):
    return C.composition(run_of(spark, d, None).corpus)


_REFERENCES = "&(lt|gt|quot|#39|apos|nbsp|copy|middot|amp);"
_CONTROLS = "[\\x00-\\x08\\x0B\\x0C\\x0E-\\x1F\\x7F\\x{FEFF}]|\\r|\\x{2028}|\\x{2029}|\\x{85}"
_OWN = P3.replace("FROM p2 WHERE lang = 'en'", "FROM cl WHERE role = 'A'")
_DEFECTS = f"""{UPSIG.replace(P3, _OWN)}, {CLUSTERS}, d AS (
 SELECT 'exact_attributed' AS defect, (SELECT count(*) FROM raw WHERE role = 'A') AS n_of, (SELECT count(*) FROM raw WHERE role = 'A') - (SELECT count(*) FROM p1 WHERE role = 'A') AS n_defect
 UNION ALL SELECT 'exact_within', (SELECT count(*) FROM raw WHERE role = 'A'), (SELECT count(*) - count(DISTINCT k) FROM raw WHERE role = 'A')
 UNION ALL SELECT 'repaired_among_survivors', count(*), count(*) FILTER (regexp_matches(text, '{_REFERENCES}') OR regexp_matches(text, '{_CONTROLS}')) FROM p2 WHERE role = 'A'
 UNION ALL SELECT 'near_among_exact_unique', (SELECT count(*) FROM p3), count(*) - count(DISTINCT component) FROM clusters)
 SELECT defect, n_of, n_defect, CASE WHEN n_of > 0 THEN round(n_defect / n_of, 6) ELSE 0 END AS rate FROM d"""


@query("defects", _DEFECTS)
def defects(spark, d):
    return C.defects(run_of(spark, d))


@query("obj_impurity", f"WITH {RAW}, {P1}, {P2} SELECT count(*) AS n_docs, count(*) FILTER (lang <> 'en') AS n_foreign FROM p2")
def obj_impurity(spark, d):
    docs = run_of(spark, d).cleaned
    return docs.agg(F.count("*").alias("n_docs"), F.count_if(~F.col("lang").eqNullSafe(F.lit("en"))).alias("n_foreign"))


@query("obj_redundancy", f"{UPSIG}, {CLUSTERS} SELECT round((count(*) - count(DISTINCT component)) / (SELECT count(*) FROM p3), 6) AS redundancy FROM clusters")
def obj_redundancy(spark, d):
    return spark.createDataFrame([(round(objective.redundancy(run_of(spark, d).p3), 6),)], "redundancy double")


@query("def_check", f"{UP5} SELECT 'purity' AS property, count(*) FILTER (lang <> 'en') AS n_violations FROM p5 UNION ALL SELECT 'novelty', count(*) FROM brute WHERE jaccard >= 0.8 AND a IN (SELECT doc_id FROM p5) AND b IN (SELECT doc_id FROM p5) UNION ALL SELECT 'quality', count(*) FROM p5 JOIN scored USING (doc_id) WHERE coverage < 0.9")
def def_check(spark, d):
    run = run_of(spark, d)
    return C.check_definition(run.corpus, run.predicted, run.scored, "en", 0.8, 0.9)


@query("audit_sample", f"{UP5} SELECT doc_id, quality FROM p5 LEFT JOIN labels USING (doc_id) ORDER BY md5('audit|0|' || doc_id) LIMIT 20")
def audit_sample(spark, d):
    sample = C.audit_sample(run_of(spark, d).corpus)
    return sample.join(table(spark, d, "labels"), "doc_id", "left").select("doc_id", "quality")


#: What stands for a phase that is left out.
_LEFT_OUT = {
    1: (P1, "p1 AS (SELECT * FROM raw)"),
    2: (" FROM cl WHERE len(string_split(clean, ' ')) >= 50)", " FROM cl)"),
    3: (P3, "p3 AS (SELECT * FROM p2)"),
    4: (P4, "p4 AS (SELECT * FROM p3)"),
    5: (P5, "p5 AS (SELECT * FROM p4)"),
}


def _ablation_sql() -> str:
    whole = [(0, UP5), *((k, UP5.replace(*_LEFT_OUT[k])) for k in _LEFT_OUT)]
    return " UNION ALL ".join(f"SELECT {k} AS skipped, ({sql} SELECT count(*) FROM p5) AS n_docs" for k, sql in whole)


@query("ablation_counts", _ablation_sql())
def ablation_counts(spark, d):
    return objective.ablation_counts(run_of(spark, d))


_TARGETS = ("de", "en", "es", "fr")


@query("targets", " UNION ALL ".join(f"SELECT '{t}' AS target, ({UP5.replace(P3, P3.replace('en', t))} SELECT count(*) FROM p5) AS n_docs" for t in _TARGETS))
def targets(spark, d):
    """Final documents with each language as the target."""
    rows = [(t, C.CorpusRun(table(spark, d), Config(target=t), C.gold, base="md5").corpus.count()) for t in _TARGETS]
    return spark.createDataFrame(rows, "target string, n_docs long")


_PARAGRAPHS = f"l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS place FROM documents), n AS (SELECT *, regexp_replace(lower(trim(regexp_replace(line, '{WS}', ' ', 'g'))), '[0-9]', '0', 'g') AS norm FROM l)"


@query("base_paragraph_dedup", f"WITH {_PARAGRAPHS} SELECT doc_id, CAST(place AS BIGINT) AS place, line AS paragraph FROM n WHERE norm <> '' QUALIFY row_number() OVER (PARTITION BY norm ORDER BY doc_id, place) = 1")
def base_paragraph_dedup(spark, d):
    return objective.paragraph_dedup(table(spark, d))


@query("base_paragraph_pipeline")
def base_paragraph_pipeline(spark, d):
    docs = table(spark, d)
    run = run_of(spark, d, None)
    return objective.paragraph_pipeline(docs, run.identify, "en", run.seed)
