"""The queries of the text operators, with the columns their contracts fix, and SQL where it can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table
from .decontam import decontaminate
from .exact_dedup import exact_duplicates
from .html_extract import extract_main_text
from .langid import identify_languages
from .line_dedup import duplicate_lines
from .mixing import GOLDEN, mix_sources
from .ngram_join import ngram_jaccard_components
from .pii import replace_pii
from .quality_fm import score_quality
from .secrets import scan_secrets

#: Key of the example query; a deployment passes its own.
EXAMPLE_KEY = b"example key, not a secret"


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(table(spark, sf_dir, "documents"), (3, 1, 2), 1.5).select("doc_id", "size", "source_size", "target", "taken", "first_slot", "n_pieces")


def op2_pii_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = replace_pii(table(spark, sf_dir, "documents"), EXAMPLE_KEY)
    return found.select("doc_id", "text", F.size("spans").cast("long").alias("n_replaced"), F.array_join(F.transform("spans", lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",").alias("spans"))


def op3_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_jaccard_components(table(spark, sf_dir, "documents"), n=4, num=85, den=100).select("doc_id", "n_shingles", "component_id")


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return duplicate_lines(table(spark, sf_dir, "documents"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), 13, 1, 20)
    return found.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"), "contaminated")


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_duplicates(table(spark, sf_dir, "documents"))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_secrets(table(spark, sf_dir, "documents"))
    of = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    text = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    base = F.filter("spans", lambda s: s["kind"] != "guess")
    costs = F.filter(F.transform("spans", lambda s: s["log10_guesses"]), lambda x: x.isNotNull())
    weakest, strongest = F.round(F.array_min(costs), 6), F.round(F.array_max(costs), 6)
    return found.select("doc_id", of("assign"), of("access"), of("hex"), F.sha2(text(base), 256).alias("base_sha256"), text("spans").alias("spans"), weakest.alias("least_log10_guesses"), strongest.alias("most_log10_guesses"))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify_languages(table(spark, sf_dir, "documents"))


def op9_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_main_text(table(spark, sf_dir, "pages"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


# --- SQL ----------------------------------------------------------------------------------------------------------

OP1_SQL = r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, list_extract([3.0::DOUBLE, 1.0::DOUBLE, 2.0::DOUBLE], ((row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 + 1)::INT) AS weight, source_size * 2.0::DOUBLE AS cap FROM s),
r AS (SELECT *, cap / weight AS ratio FROM w),
l AS (SELECT *, ((SELECT sum(source_size) FROM s) * 1.5::DOUBLE - coalesce(sum(cap) OVER o, 0)) / ((SELECT sum(weight) FROM w) - coalesce(sum(weight) OVER o, 0)) AS level
      FROM r WINDOW o AS (ORDER BY ratio, source IS NULL, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
t AS (SELECT source, source_size, CASE WHEN ratio <= level THEN cap ELSE weight * (SELECT arg_min(level, (ratio, source IS NULL, source)) FROM l WHERE ratio > level) END::DOUBLE AS target FROM l),
i AS (SELECT *, row_number() OVER (ORDER BY source IS NULL, source) AS source_id FROM t),
b AS (SELECT greatest(1, least(4096, sum(source_size)::BIGINT // (256 * count(*)))) AS block FROM i),
e AS (SELECT source_id, ceil(floor(target) / block)::BIGINT AS need FROM i, b),
f AS (SELECT *, sum(need) OVER (ORDER BY source_id) AS upto FROM e WHERE need > 0),
g AS (SELECT t AS slot, (high * 'GOLDEN_HIGH'::DOUBLE + low * 'GOLDEN_LOW'::DOUBLE) AS v FROM
      (SELECT t, ((t + 1) // 1048576)::DOUBLE AS high, ((t + 1) % 1048576)::DOUBLE AS low FROM (SELECT unnest(range(0, (SELECT coalesce(sum(need), 0)::BIGINT FROM f))) AS t))),
h AS (SELECT slot, source_id, need, row_number() OVER (PARTITION BY source_id ORDER BY slot) - 1 AS rank
      FROM (SELECT slot, (v - floor(v)) * (SELECT sum(need) FROM f)::DOUBLE AS x FROM g) JOIN f ON x >= upto - need AND x < upto),
k AS (SELECT slot, source_id, rank FROM h WHERE rank < need),
q AS (SELECT f.source_id, need, coalesce(got, 0) AS got FROM f LEFT JOIN (SELECT source_id, count(*) AS got FROM k GROUP BY 1) c ON c.source_id = f.source_id),
plan AS (SELECT * FROM k UNION ALL SELECT (SELECT sum(need) FROM f) + rank AS slot, source_id, rank FROM (SELECT source_id, unnest(range(got, need)) AS rank FROM q WHERE got < need)),
p AS (SELECT d.*, source_id, source_size, target, coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY md5(doc_id::VARCHAR), doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start
      FROM d JOIN i ON d.source IS NOT DISTINCT FROM i.source),
r2 AS (SELECT source_id, start, pos, least(pos + size, floor(target)::BIGINT) AS stop FROM (SELECT *, unnest([start, start + source_size]) AS pos FROM p WHERE size > 0)),
pc AS (SELECT source_id, start, pos, stop, block, unnest(range(pos // block, (stop - 1) // block + 1)) AS rank FROM r2, b WHERE pos < stop),
taken AS (SELECT pc.source_id, start, sum(least(stop, (pc.rank + 1) * block) - greatest(pos, pc.rank * block)) AS taken, min(slot) AS first_slot, count(*) AS n_pieces
      FROM pc JOIN plan ON plan.source_id = pc.source_id AND plan.rank = pc.rank GROUP BY 1, 2)
SELECT doc_id, size::BIGINT AS size, source_size, target, coalesce(taken, 0)::BIGINT AS taken, coalesce(first_slot, -1)::BIGINT AS first_slot, coalesce(n_pieces, 0)::BIGINT AS n_pieces
FROM p LEFT JOIN taken ON size > 0 AND taken.source_id = p.source_id AND taken.start = p.start""".replace("GOLDEN_HIGH", repr((GOLDEN * 1048576) % 1.0)).replace("GOLDEN_LOW", repr(GOLDEN))

OP3_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 4 THEN [array_to_string(ws, ' ')]
        ELSE list_transform(range(1, len(ws) - 2), lambda i: array_to_string(ws[i:i + 3], ' ')) END) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
r(doc_id, other) AS (SELECT doc_id, doc_id FROM w UNION SELECT r.doc_id, l.b FROM r JOIN l ON l.a = r.other)
SELECT r.doc_id, coalesce(any_value(n.n), 0)::BIGINT AS n_shingles, min(r.other) AS component_id FROM r LEFT JOIN n ON n.doc_id = r.doc_id GROUP BY r.doc_id"""

OP5_SQL = r"""
WITH t AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
w AS (SELECT DISTINCT item_id::VARCHAR AS item_id, least(len(ws), 13) AS n, array_to_string(ws[i:i + least(len(ws), 13) - 1], ' ') AS g
      FROM (SELECT *, unnest(range(1, len(ws) - least(len(ws), 13) + 2)) AS i FROM b WHERE len(ws) > 0)),
sizes AS (SELECT DISTINCT n FROM w),
x AS (SELECT doc_id, i, n, array_to_string(ws[i:i + n - 1], ' ') AS g FROM (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS i FROM t, sizes WHERE len(ws) >= n)),
h AS (SELECT doc_id, i, x.n, item_id FROM x JOIN w ON x.n = w.n AND x.g = w.g),
c AS (SELECT doc_id, count(DISTINCT i + k) AS n_hit FROM (SELECT doc_id, i, unnest(range(0, n)) AS k FROM h) GROUP BY doc_id),
m AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, sha256(string_agg(DISTINCT item_id, ',' ORDER BY item_id)) AS items_sha256 FROM h GROUP BY doc_id)
SELECT t.doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, coalesce(items_sha256, sha256('')) AS items_sha256,
  coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
FROM t LEFT JOIN c ON c.doc_id = t.doc_id LEFT JOIN m ON m.doc_id = t.doc_id"""

OP6_SQL = r"""
WITH t AS (SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256 FROM documents)
SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size, doc_id = max(doc_id) OVER g AS kept, text_sha256 FROM t WINDOW g AS (PARTITION BY text_sha256)"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_mix_sources": op1_mix_sources,
        "op2_pii_pseudonyms": op2_pii_pseudonyms,
        "op3_ngram_jaccard": op3_ngram_jaccard,
        "op4_line_dedup": op4_line_dedup,
        "op5_decontaminate": op5_decontaminate,
        "op6_exact_dedup": op6_exact_dedup,
        "op7_secret_scan": op7_secret_scan,
        "op8_language_id": op8_language_id,
        "op9_html_extract": op9_html_extract,
        "op10_quality": op10_quality,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_mix_sources": OP1_SQL, "op3_ngram_jaccard": OP3_SQL, "op5_decontaminate": OP5_SQL, "op6_exact_dedup": OP6_SQL}
