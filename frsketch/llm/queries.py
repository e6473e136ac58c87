"""The registered queries of this subpackage and their DuckDB texts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


# op3: rules (host, path), as the contract states them, and the listed sites of this deployment
URL_RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]
LISTED_URLS = [("casino-win.example.com", "/", "block"), ("spam-farm.example.com", "/", "block"), ("casino-win.example.net", "/", "block"), ("casino-win.example.org", "/", "block"), ("spam-farm.example.net", "/", "block"), ("spam-farm.example.org", "/", "block")]


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from frsketch.llm.simhash import hex_digits, near_duplicates

    out = near_duplicates(table(spark, sf_dir, "documents"), most=4, width=4)
    return out.select("doc_id", hex_digits(F.col("fp")).alias("fingerprint"), "component_id")


def op2_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    from frsketch.llm.suffix_dedup import without_repeats

    return without_repeats(table(spark, sf_dir, "documents"), keep_bytes=False)


def op3_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from frsketch.llm.url_filter import judge_urls, url_list

    out = judge_urls(table(spark, sf_dir, "pages"), url_list(spark, URL_RULES), url_list(spark, LISTED_URLS))
    return out.select("page_id", "host", "path", "rule", "verdict")


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from frsketch.llm.token_counts import count_tokens

    return count_tokens(table(spark, sf_dir, "documents"), tokenizer_file("byte_bpe_50k.json"), limit=512)


def op5_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from frsketch.llm.bpe import encode_frame

    return encode_frame(table(spark, sf_dir, "documents"), tokenizer_file("byte_bpe_50k.tiktoken"), with_ids=False)


def op6_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    import uuid

    from frsketch.llm.shared import shared_dir
    from frsketch.llm.token_store import read_tokens, write_tokens

    path = f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
    write_tokens(table(spark, sf_dir, "documents"), path, tokenizer_file("byte_bpe_50k.json"), end_id=0)
    return read_tokens(spark, path)


def op7_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``documents`` has no file names: a document lies at source/lang/doc_id, and one that is mostly
    licence text stands for its directory's licence file."""
    from frsketch.llm.license_scan import scan_licences

    path = F.concat_ws("/", "source", "lang", F.col("doc_id").cast("string"))
    return scan_licences(table(spark, sf_dir, "documents"), path, F.col("share") >= 0.5)


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from frsketch.llm.decontaminate import find_leaks

    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from frsketch.llm.quality import quality_frame

    return quality_frame(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).drop("score")


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from frsketch.llm.toxicity import toxicity_frame

    return toxicity_frame(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).drop("ratio")


QUERIES = {
    "op1_simhash": op1_simhash,
    "op2_suffix_array": op2_suffix_array,
    "op3_url_rules": op3_url_rules,
    "op4_token_counts": op4_token_counts,
    "op5_byte_bpe": op5_byte_bpe,
    "op6_token_store": op6_token_store,
    "op7_licences": op7_licences,
    "op8_quality_rules": op8_quality_rules,
    "op9_toxicity": op9_toxicity,
    "op10_decontamination": op10_decontamination,
}

def _values(rows: list[tuple[str, str, str]]) -> str:
    return ", ".join(f"('{h}', '{p}', '{a}')" for h, p, a in rows)


def _licence_sql() -> str:
    from frsketch.llm.license_scan import LEAST, SPLIT, TEMPLATES

    def terms(text: str) -> str:
        return f"list_filter(list_transform(regexp_split_to_array(lower({text}), '{SPLIT}'), lambda x: trim(x, '.-')), lambda x: x <> '')"

    rows = ", ".join(f"('{n}', '{t}')" for n, t in TEMPLATES.items())
    return f"""
WITH d AS (SELECT doc_id, concat_ws('/', source, lang, doc_id::VARCHAR) AS path, concat_ws('/', source, lang) AS dir, coalesce(text, '') AS text FROM documents),
n AS (SELECT count(*) AS n FROM d),
tt AS (SELECT name, unnest({terms('text')}) AS term FROM (VALUES {rows}) v(name, text)),
vocab AS (SELECT DISTINCT term FROM tt),
df AS (SELECT term, count(*) AS df FROM (SELECT DISTINCT doc_id, unnest({terms('text')}) AS term FROM d) SEMI JOIN vocab USING (term) GROUP BY term),
idf AS (SELECT term, ln((1 + n) / (1 + coalesce(df, 0))) + 1 AS idf FROM vocab LEFT JOIN df USING (term), n),
tw AS (SELECT name, term, count(*) * any_value(idf) AS w FROM tt JOIN idf USING (term) GROUP BY name, term),
tn AS (SELECT name, term, w / sqrt(sum(w * w) OVER (PARTITION BY name)) AS weight FROM tw),
ls AS (SELECT doc_id, i AS line, {terms("string_split(text, chr(10))[i]")} AS terms FROM (SELECT doc_id, text, unnest(range(1, len(string_split(text, chr(10))) + 1)) AS i FROM d)),
tf AS (SELECT doc_id, line, len(terms) AS n, term, count(*) AS tf FROM (SELECT doc_id, line, terms, unnest(terms) AS term FROM ls WHERE list_has_any(terms, (SELECT list(term) FROM vocab))) GROUP BY ALL),
w AS (SELECT tf.*, tf * coalesce(idf, (SELECT ln(1 + n) + 1 FROM n)) AS w FROM tf LEFT JOIN idf USING (term)),
nm AS (SELECT doc_id, line, n, sqrt(sum(w * w)) AS norm FROM w GROUP BY ALL),
hit AS (SELECT doc_id, line, n, name, round(dot / norm, 9) AS cosine FROM (SELECT doc_id, line, name, sum(w * weight) AS dot FROM w JOIN tn USING (term) GROUP BY ALL) JOIN nm USING (doc_id, line) WHERE round(dot / norm, 9) >= {LEAST}),
ln_ AS (SELECT doc_id, line, n, max(cosine) AS cosine, first(name ORDER BY cosine DESC, name) AS name FROM hit GROUP BY doc_id, line, n),
own AS (SELECT doc_id, first(name ORDER BY cosine DESC, name) AS own, max(cosine) AS cosine, count(*) AS n_lines, sum(n) AS terms_in FROM ln_ GROUP BY doc_id),
g AS (SELECT d.doc_id, path, dir, own, cosine, n_lines, own IS NOT NULL AND terms_in >= 0.5 * len({terms('text')}) AS speaks FROM d LEFT JOIN own USING (doc_id)),
sp AS (SELECT dir, first(own ORDER BY cosine DESC, own) AS said FROM g WHERE speaks GROUP BY dir),
up AS (SELECT dir, k AS depth, array_to_string(string_split(dir, '/')[1:k], '/') AS above FROM (SELECT DISTINCT dir FROM g), range(0, 3) r(k)),
near AS (SELECT up.dir, first(said ORDER BY depth DESC) AS said, first(above ORDER BY depth DESC) AS from_dir FROM up JOIN sp ON sp.dir = above GROUP BY up.dir)
SELECT doc_id, path, own, cosine, coalesce(n_lines, 0) AS n_lines, coalesce(own, said) AS licence, CASE WHEN own IS NULL THEN from_dir END AS from_dir FROM g LEFT JOIN near USING (dir)"""


ORACLE_SQL: dict[str, str] = {
    "op3_url_rules": f"""
WITH entry(eh, ep, act, kind) AS (
  SELECT *, 1 FROM (VALUES {_values(URL_RULES)}) UNION ALL SELECT *, 0 FROM (VALUES {_values(LISTED_URLS)})
), cut AS (
  SELECT page_id, CASE WHEN coalesce(position('://' IN url), 0) = 0 THEN '' ELSE substr(url, position('://' IN url) + 3) END AS rest FROM pages
), part AS (
  SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut
), fit AS (
  SELECT page_id, host, path, arg_max(struct_pack(k := kind, e := eh || ep, a := act), kind * 100000 + length(eh || ep)) AS best
  FROM part LEFT JOIN entry ON (host = eh OR ends_with(host, '.' || eh)) AND starts_with(path, ep)
  GROUP BY ALL
)
SELECT page_id, host, path, CASE WHEN best.k = 1 THEN best.e END AS rule, coalesce(best.a, 'allow') AS verdict FROM fit""",
    "op7_licences": _licence_sql(),
}
