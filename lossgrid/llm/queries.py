"""One query for each training-data operator over its whole table, with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

#: Vocabulary of a public tokenizer.
TOKENIZER = "/opt/tokenizers/piece_bpe_32k.model"

Query = Callable[[SparkSession, str], DataFrame]


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontaminate import contamination

    return contamination(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op2_mix_to_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mix

    return mix(_table(spark, sf_dir, "documents"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language import identify

    return identify(_table(spark, sf_dir, "documents"))


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .exact import exact_duplicates

    return exact_duplicates(_table(spark, sf_dir, "documents"))


def op5_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substring import repeated_substrings

    return repeated_substrings(_table(spark, sf_dir, "documents"), window=35)


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .lines import removed_lines

    return removed_lines(_table(spark, sf_dir, "documents"), percent=80)


def op7_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .lm import language_model_scores

    return language_model_scores(_table(spark, sf_dir, "documents"))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .tokens import token_counts, piece_scores

    return token_counts(_table(spark, sf_dir, "documents"), piece_scores(TOKENIZER))


def op9_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .html import main_text

    return main_text(_table(spark, sf_dir, "pages"))


def op10_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .minhash import near_duplicates

    return near_duplicates(_table(spark, sf_dir, "documents"), shingle=2, percent=80)


def queries() -> dict[str, Query]:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f)}


def oracle_sql() -> dict[str, str]:
    return {"op1_benchmark_decontamination": OP1, "op4_exact_dedup": OP4, "op5_substring_dedup": OP5, "op10_minhash_near_dedup": OP10}


_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP1 = f"""
WITH i AS (SELECT item_id, {_WORDS} AS w FROM benchmark),
     iw AS (SELECT DISTINCT item_id, least(len(w), 10) AS size, array_to_string(w[k : k + 9], ' ') AS phrase
            FROM (SELECT item_id, w, unnest(range(1, greatest(2, len(w) - 8))) AS k FROM i WHERE len(w) > 0)),
     d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
     sizes AS (SELECT DISTINCT size FROM iw),
     dw AS (SELECT doc_id, size, k, array_to_string(w[k : k + size - 1], ' ') AS phrase
            FROM (SELECT doc_id, w, size, unnest(range(1, len(w) - size + 2)) AS k FROM d, sizes WHERE len(w) >= size)),
     m AS (SELECT dw.doc_id, dw.k, dw.size, iw.item_id FROM dw JOIN iw USING (size, phrase)),
     h AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + size)) AS p FROM m) GROUP BY 1),
     n AS (SELECT doc_id, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS names
           FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS x FROM m) GROUP BY 1)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN n USING (doc_id)
"""

OP5 = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
     g AS (SELECT doc_id, k, md5(array_to_string(w[k : k + 34], ' ')) AS h
           FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS k FROM d WHERE len(w) >= 35)),
     r AS (SELECT doc_id, k FROM g WHERE h IN (SELECT h FROM g GROUP BY h HAVING count(*) > 1)),
     x AS (SELECT doc_id, list(DISTINCT p) AS gone FROM (SELECT doc_id, unnest(range(k, k + 35)) AS p FROM r) GROUP BY 1),
     t AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS p FROM d),
     k AS (SELECT t.doc_id, string_agg(t.w[t.p], ' ' ORDER BY t.p) AS kept, count(*) AS n
           FROM t LEFT JOIN (SELECT doc_id, unnest(gone) AS p FROM x) y ON t.doc_id = y.doc_id AND t.p = y.p WHERE y.p IS NULL GROUP BY 1)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id)
"""

_NORMALISED = "replace(replace(replace(replace(replace(replace(coalesce(text, ''), ' ', ''), chr(9), ''), chr(10), ''), chr(11), ''), chr(12), ''), chr(13), '')"

OP4 = f"""
WITH d AS (SELECT doc_id, coalesce(length(text), 0) AS size, sha256({_NORMALISED}) AS text_sha256 FROM documents)
SELECT doc_id,
       first_value(doc_id) OVER w AS keep_id,
       count(*) OVER (PARTITION BY text_sha256) AS group_size,
       doc_id = first_value(doc_id) OVER w AS kept,
       text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256 ORDER BY size DESC, doc_id)
"""

OP10 = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) = 1 THEN [w[1]] ELSE list_distinct(list_transform(range(1, len(w)), lambda k: w[k] || ' ' || w[k + 1])) END AS s FROM d),
n AS (SELECT doc_id, s, len(s) AS n FROM s),
e AS (SELECT x.doc_id AS a, y.doc_id AS b FROM n x JOIN n y ON x.doc_id < y.doc_id AND x.n > 0 AND y.n > 0 AND 100 * least(x.n, y.n) >= 80 * greatest(x.n, y.n)
      WHERE 180 * len(list_intersect(x.s, y.s)) >= 80 * (x.n + y.n)),
l AS (SELECT a, b FROM e UNION SELECT b, a FROM e),
r(doc_id, top) AS (SELECT doc_id, doc_id FROM n UNION SELECT l.b, r.top FROM r JOIN l ON l.a = r.doc_id AND r.top < l.b),
c AS (SELECT doc_id, min(top) AS component_id FROM r GROUP BY 1)
SELECT n.doc_id, CAST(n AS BIGINT) AS n_shingles, component_id, n.doc_id = component_id AS kept FROM n JOIN c USING (doc_id)
"""
