"""The registered queries of the corpus operators and their SQL, where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from incstate.llm import (
    collision_links,
    cube_mix,
    hilbert_pack,
    kd_shards,
    knn_quality,
    license_scan,
    lsh_forest,
    rank_bpe,
    rlz_dedup,
    tree_rules,
)
from incstate.llm.common import read_table


def op1_cube_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cube_mix.decisions(read_table(spark, sf_dir, "documents"))


def op2_collision_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return collision_links.collision_links(read_table(spark, sf_dir, "embeddings"))


def op3_kd_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kd_shards.kd_shards(read_table(spark, sf_dir, "documents"))


def op4_hilbert_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hilbert_pack.packing(read_table(spark, sf_dir, "documents"), public_tokenizers.path(hilbert_pack.VOCABULARY))


def op5_lsh_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lsh_forest.near_duplicates(read_table(spark, sf_dir, "documents"))


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.license_digest(read_table(spark, sf_dir, "documents"))


def op7_rlz_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rlz_dedup.digest(read_table(spark, sf_dir, "documents"))


def op8_rank_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rank_bpe.token_counts(read_table(spark, sf_dir, "documents"), public_tokenizers.path(rank_bpe.VOCABULARY))


def op9_tree_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree_rules.quality_rules(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op10_knn_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return knn_quality.quality_scores(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_cube_mix": op1_cube_mix,
    "op2_collision_links": op2_collision_links,
    "op3_kd_shards": op3_kd_shards,
    "op4_hilbert_pack": op4_hilbert_pack,
    "op5_lsh_forest": op5_lsh_forest,
    "op6_license_scan": op6_license_scan,
    "op7_rlz_dedup": op7_rlz_dedup,
    "op8_rank_bpe": op8_rank_bpe,
    "op9_tree_rules": op9_tree_rules,
    "op10_knn_quality": op10_knn_quality,
}

#: Words of a text, for DuckDB.
WORDS_SQL = r"regexp_extract_all({text}, '[^\x20\x09-\x0D]+')"

OP2_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings
), good AS (
  SELECT vec_id, e FROM v
  WHERE e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND len(list_filter(e, lambda x: x <> 0)) > 0
), links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM good a JOIN good b
    ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) AND list_cosine_similarity(a.e, b.e) >= CAST(0.9 AS DOUBLE)
), reach AS (
  SELECT vec_id AS a, vec_id AS b FROM v UNION SELECT reach.a, links.b FROM reach JOIN links ON reach.b = links.a
), groups AS (SELECT a, min(b) AS component_id FROM reach GROUP BY a)
SELECT v.vec_id, (SELECT count(*) FROM links WHERE links.a = v.vec_id) AS n_links, component_id,
  v.vec_id = component_id AS kept
FROM v JOIN groups ON groups.a = v.vec_id
"""

OP5_SQL = f"""
WITH RECURSIVE w AS (
  SELECT doc_id, {WORDS_SQL.format(text="translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')")} AS words
  FROM documents
), s AS (
  SELECT doc_id, CASE WHEN len(words) = 0 THEN [] WHEN len(words) < 4 THEN [array_to_string(words, ' ')]
    ELSE list_distinct([array_to_string(words[i:i + 3], ' ') FOR i IN range(1, len(words) - 2)]) END AS shingles
  FROM w
), n AS (SELECT doc_id, len(shingles) AS n FROM s),
x AS (SELECT doc_id, unnest(shingles) AS shingle FROM s),
pairs AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS met FROM x a JOIN x b ON a.shingle = b.shingle AND a.doc_id <> b.doc_id
  GROUP BY ALL
), links AS (
  SELECT a, b FROM pairs JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b
  WHERE 100 * met >= 80 * (na.n + nb.n - met)
), reach AS (
  SELECT doc_id AS a, doc_id AS b FROM n UNION SELECT reach.a, links.b FROM reach JOIN links ON reach.b = links.a
), groups AS (SELECT a, min(b) AS component_id FROM reach GROUP BY a)
SELECT n.doc_id, CAST(n.n AS BIGINT) AS n_shingles, component_id, n.doc_id = component_id AS kept
FROM n JOIN groups ON groups.a = n.doc_id
"""

OP7_SQL = f"""
WITH w AS (SELECT doc_id, {WORDS_SQL.format(text="coalesce(text, '')")} AS words FROM documents),
win AS (
  SELECT doc_id, i, md5(array_to_string(words[i:i + 34], ' ')) AS s
  FROM (SELECT doc_id, words, unnest(range(1, len(words) - 33)) AS i FROM w)
), twice AS (SELECT s FROM win GROUP BY s HAVING count(*) > 1),
gone AS (
  SELECT DISTINCT doc_id, i + k AS i FROM win SEMI JOIN twice USING (s), (SELECT unnest(range(0, 35)) AS k)
), lost AS (SELECT doc_id, list(i) AS lost FROM gone GROUP BY doc_id)
SELECT w.doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(coalesce(len(lost), 0) AS BIGINT) AS n_removed,
  sha256(array_to_string(CASE WHEN lost IS NULL THEN words
    ELSE list_transform(list_filter(range(1, len(words) + 1), lambda i: NOT list_contains(lost, i)), lambda i: words[i]) END, ' ')) AS kept_sha256
FROM w LEFT JOIN lost USING (doc_id)
"""

_TEMPLATE_ROWS = ", ".join("('{}', '{}')".format(k, v.replace("'", "''")) for k, v in license_scan.TEMPLATES.items())
_PLAIN = r"regexp_extract_all(translate({text}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP6_SQL = f"""
WITH t AS (SELECT name, {_PLAIN.format(text="body")} AS w FROM (VALUES {_TEMPLATE_ROWS}) v(name, body)),
ts AS (SELECT name, i, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT name, w, unnest(range(1, len(w) - 3)) AS i FROM t)),
tn AS (SELECT name, count(*) AS size, count(DISTINCT s) AS distinct_size FROM ts GROUP BY name),
d AS (SELECT doc_id, {_PLAIN.format(text="coalesce(text, '')")} AS w FROM documents),
ds AS (SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM d)),
hit AS (SELECT DISTINCT doc_id, name, ds.i, s FROM ds JOIN ts USING (s)),
found AS (
  SELECT a.doc_id, a.name FROM hit a JOIN hit b ON a.doc_id = b.doc_id AND a.name = b.name JOIN tn ON tn.name = a.name
    AND b.i BETWEEN a.i AND a.i + tn.size - 1
  GROUP BY a.doc_id, a.name, a.i, tn.distinct_size HAVING count(DISTINCT b.s) >= CAST(0.8 AS DOUBLE) * tn.distinct_size
), names AS (SELECT DISTINCT doc_id, regexp_replace(name, ' [(].*', '') AS name FROM found)
SELECT d.doc_id, count(name) AS n_licenses, coalesce(string_agg(name, ',' ORDER BY name), '') AS licenses
FROM d LEFT JOIN names ON names.doc_id = d.doc_id GROUP BY d.doc_id
"""

ORACLES: dict[str, str] = {
    "op2_collision_links": OP2_SQL,
    "op5_lsh_forest": OP5_SQL,
    "op6_license_scan": OP6_SQL,
    "op7_rlz_dedup": OP7_SQL,
}
