"""The queries of this subpackage, with production parameters, over whole tables; SQL twins where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe_count, decontaminate, langid, mixing, quality, sentence_spans, setjoin, token_files, toxicity, url_rules

#: Tokenizer file of the token operators (a parameter; the file is never part of this repository).
TOKENIZER = "byte_bpe_50k.json"


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.assess(table(spark, sf_dir, "documents"))


def op2_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return setjoin.join_components(table(spark, sf_dir, "documents")).drop("fp")


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_words(table(spark, sf_dir, "documents"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_count.token_counts(table(spark, sf_dir, "documents"), tokenizer_path())


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return langid.identify(docs, langid.fit(docs))


def op7_sentence_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentence_spans.remove_repeats(table(spark, sf_dir, "documents"))


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.round_trip(table(spark, sf_dir, "documents"), tokenizer_path())


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


#: The rules of the pages query (fixed values).
URL_RULES = [
    url_rules.Rule("com", "/en/", "block"),
    url_rules.Rule("example.com", "/en/7", "allow"),
    url_rules.Rule("net", "/de/", "allow"),
    url_rules.Rule("example.net", "/de/8", "block"),
    url_rules.Rule("org", "/es/", "block"),
]


def op10_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_rules.judge_urls(table(spark, sf_dir, "pages"), URL_RULES)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        f.__name__: f
        for f in (
            op1_quality,
            op2_ngram_join,
            op3_mixing,
            op4_toxicity,
            op5_token_counts,
            op6_language,
            op7_sentence_spans,
            op8_token_files,
            op9_decontaminate,
            op10_url_rules,
        )
    }


UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

JOIN_SQL = rf"""WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
  s AS (SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] ELSE list_distinct(list_transform(generate_series(1, greatest(1, len(ws) - 4)),
    lambda i: array_to_string(list_slice(ws, i, i + 4), ' '))) END AS sh FROM w),
  t AS MATERIALIZED (SELECT doc_id, len(sh) AS n, unnest(sh) AS x FROM s),
  m AS (SELECT a.doc_id AS a, b.doc_id AS b, any_value(a.n) AS na, any_value(b.n) AS nb, count(*) AS k FROM t a JOIN t b ON a.x = b.x AND a.doc_id <> b.doc_id GROUP BY 1, 2),
  links AS MATERIALIZED (SELECT a, b FROM m WHERE 100 * k >= 80 * (na + nb - k)),
  reach(a, b) AS (SELECT a, b FROM links UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a)
  SELECT s.doc_id, CAST(len(sh) AS BIGINT) AS n_shingles, least(s.doc_id, min(r.b)) AS component_id FROM s LEFT JOIN reach r ON r.a = s.doc_id GROUP BY s.doc_id, len(sh)"""

_CLEAN = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
LEAKS_SQL = f"""WITH dw AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{_CLEAN}') AS ws FROM documents),
  iw AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{_CLEAN}') AS ws FROM benchmark),
  win AS (SELECT DISTINCT item_id, least(10, len(ws)) AS n, array_to_string(list_slice(ws, i, i + 9), ' ') AS x
    FROM (SELECT item_id, ws, unnest(generate_series(1, greatest(1, len(ws) - 9))) AS i FROM iw WHERE len(ws) > 0)),
  g AS (SELECT doc_id, n, i, array_to_string(list_slice(ws, i, i + n - 1), ' ') AS x FROM
    (SELECT doc_id, ws, n, unnest(generate_series(1, len(ws) - n + 1)) AS i FROM dw, (SELECT DISTINCT n FROM win) WHERE len(ws) >= n)),
  h AS MATERIALIZED (SELECT g.doc_id, g.i, g.n, win.item_id FROM g JOIN win USING (n, x)),
  hit AS (SELECT doc_id, count(DISTINCT p) AS k FROM (SELECT doc_id, unnest(generate_series(i, i + n - 1)) AS p FROM h) GROUP BY 1),
  it AS (SELECT doc_id, count(*) AS k, string_agg(x, ',' ORDER BY x) AS ids FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS x FROM h) GROUP BY 1)
  SELECT dw.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(hit.k, 0) AS n_hit, coalesce(it.k, 0) AS n_items, sha256(coalesce(it.ids, '')) AS items_sha256,
    coalesce(hit.k, 0) > 0 AS contaminated FROM dw LEFT JOIN hit USING (doc_id) LEFT JOIN it USING (doc_id)"""


CLASS_PATTERNS = [r"\x20\x09-\x0D", "a-z", "A-Z", "0-9", r"!\x22\x27()+,\-./:;=?@\[\x5C\]\^_`{}~", "#*$%&|<>", r"\x00-\x08\x0E-\x1F\x7F"]


def quality_sql() -> str:
    """Histograms, references and distances as rows of (document, language, cell)."""
    r = quality.QualityRules()
    counts = ", ".join([*(f"length(regexp_replace(t, '[^{p}]', '', 'g'))" for p in CLASS_PATTERNS), r"length(regexp_replace(t, '[\x00-\x7F]', '', 'g'))"])
    common = ", ".join(f"('{lang}', '{w}')" for lang in quality.LANGS for w in sorted(set(quality.COMMON[lang])))
    js = lambda cells, refs: f"""(SELECT row, min(js) AS js FROM (SELECT row, lang, sqrt(least(1, greatest(0, (sum(CASE WHEN p > 0 THEN p * log2(p / ((p + q) / 2)) ELSE 0 END)
        + sum(CASE WHEN q > 0 THEN q * log2(q / ((p + q) / 2)) ELSE 0 END)) / 2))) AS js
      FROM (SELECT c.row, f.lang, c.n / greatest(sum(c.n) OVER (PARTITION BY c.row, f.lang), 1) AS p, f.n / greatest(sum(f.n) OVER (PARTITION BY c.row, f.lang), 1) AS q
        FROM {cells} c JOIN {refs} f ON f.cell = c.cell AND (c.lang IS NULL OR c.lang = f.lang)) GROUP BY 1, 2) GROUP BY 1)"""  # noqa: E731
    return rf"""WITH d AS MATERIALIZED (SELECT row_number() OVER () AS row, doc_id, lang, coalesce(text, '') AS t FROM documents),
  w AS MATERIALIZED (SELECT row, doc_id, lang, t, regexp_extract_all(t, '[^ 	-]+') AS ws FROM d),
  common(lang, word) AS (VALUES {common}),
  pos AS MATERIALIZED (SELECT row, unnest(ws) AS x, generate_subscripts(ws, 1) AS i, len(ws) AS n FROM w),
  tri AS (SELECT row, i, x || chr(10) || lead(x) OVER o || chr(10) || lead(x, 2) OVER o AS k FROM pos WINDOW o AS (PARTITION BY row ORDER BY i)),
  often AS (SELECT row, unnest([i, i + 1, i + 2]) AS p FROM (SELECT row, i, count(*) OVER (PARTITION BY row, k) AS c FROM tri WHERE k IS NOT NULL) WHERE c > 1),
  rep AS (SELECT row, count(DISTINCT p) AS n FROM often GROUP BY 1),
  lines AS (SELECT row, count(*) - count(DISTINCT x) AS n FROM (SELECT row, unnest(string_split(t, chr(10))) AS x FROM d) WHERE regexp_matches(x, '[^ 	-]') GROUP BY 1),
  cc AS MATERIALIZED (SELECT row, NULL AS lang, unnest(range(8)) AS cell, CAST(unnest([{counts}]) AS DOUBLE) AS n FROM d),
  cref AS MATERIALIZED (SELECT d.lang, cell, sum(n) AS n FROM cc JOIN d USING (row) WHERE d.lang IN (SELECT lang FROM common) GROUP BY 1, 2),
  lw AS MATERIALIZED (SELECT row, translate(x, '{UPPER}', '{LOWER}') AS word, count(*) AS n FROM pos GROUP BY 1, 2),
  tot AS (SELECT row, sum(n) AS n FROM lw GROUP BY 1),
  own AS (SELECT lw.row, c.lang, lw.word AS cell, CAST(lw.n AS DOUBLE) AS n FROM lw JOIN common c USING (word)),
  cells AS (SELECT DISTINCT lang, word AS cell FROM common UNION ALL SELECT DISTINCT lang, '' FROM common),
  wc AS MATERIALIZED (SELECT t.row, e.lang, e.cell, CASE WHEN e.cell = '' THEN t.n - coalesce((SELECT sum(n) FROM own o WHERE o.row = t.row AND o.lang = e.lang), 0) ELSE coalesce(o.n, 0) END AS n
    FROM tot t CROSS JOIN cells e LEFT JOIN own o ON o.row = t.row AND o.lang = e.lang AND o.cell = e.cell),
  wref AS MATERIALIZED (SELECT wc.lang, cell, sum(n) AS n FROM wc JOIN d USING (row) WHERE d.lang = wc.lang GROUP BY 1, 2),
  cj AS ({js("cc", "cref")}), wj AS ({js("wc", "wref")}),
  f AS (SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(t) - length(regexp_replace(t, '[^ 	-]', '', 'g')) AS BIGINT) AS word_chars,
      CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, coalesce(lines.n, 0) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words,
      len(ws) < {r.min_words} OR 100 * coalesce(rep.n, 0) > {r.max_repeat_percent} * len(ws) AS base_failed,
      CASE WHEN length(t) >= {r.min_chars} THEN round(cj.js, 6) END AS class_js, CASE WHEN len(ws) >= {r.min_hist_words} THEN round(wj.js, 6) END AS word_js
    FROM w LEFT JOIN rep USING (row) LEFT JOIN lines USING (row) LEFT JOIN cj USING (row) LEFT JOIN wj USING (row))
  SELECT *, NOT base_failed AND NOT (coalesce(class_js > {r.max_class_distance}, FALSE) OR coalesce(word_js > {r.max_word_distance}, FALSE)) AS kept FROM f"""


def rules_sql(what: str) -> str:
    order = sorted(URL_RULES, key=lambda r: (-len(r.name), -len(r.host), r.name))
    return "CASE " + " ".join(f"WHEN (host = '{r.host}' OR host LIKE '%.{r.host}') AND path LIKE '{r.path}%' THEN '{getattr(r, what)}'" for r in order) + " END"


#: The given pages link to no other host, so each host's trust and distrust are its seeds; propagation itself is
#: tested against plain iteration.
URLS_SQL = rf"""WITH p AS (SELECT page_id, translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)', 1), '{UPPER}', '{LOWER}') AS host,
    regexp_extract(coalesce(url, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1) AS path FROM pages),
  q AS (SELECT *, {rules_sql("name")} AS rule, {rules_sql("verdict")} AS said FROM p),
  h AS (SELECT host, avg(CASE WHEN said = 'allow' THEN 1.0 ELSE 0.0 END) AS trust, avg(CASE WHEN said = 'block' THEN 1.0 ELSE 0.0 END) AS distrust FROM q WHERE host <> '' GROUP BY 1)
  SELECT page_id, host, path, rule, CASE WHEN said IS NOT NULL THEN said WHEN distrust >= 0.5 AND distrust > trust THEN 'block' ELSE 'allow' END AS verdict,
    trust, distrust FROM q LEFT JOIN h USING (host)"""


def oracle_sql() -> dict[str, str]:
    """Other operators rest on hashing, compression, models or tokenizers: tests hold them against brute force."""
    return {"op1_quality": quality_sql(), "op2_ngram_join": JOIN_SQL, "op9_decontaminate": LEAKS_SQL, "op10_url_rules": URLS_SQL}
