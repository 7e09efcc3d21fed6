"""Queries over the text operators, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from fairsummary.session import find_package

from . import lattice, media, neighbours, packing, personal, piece_counts, simhash, substring, token_table, toxicity


def _over(digest: Callable[..., DataFrame], *tables: str) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        find_package(spark)
        return digest(*(spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in tables))

    return query


QUERIES = {
    "op1_substring_dedup": _over(substring.digest, "documents"),
    "op2_media_column": _over(media.digest, "documents"),
    "op3_token_table": _over(token_table.digest, "documents"),
    "op4_best_fit_packing": _over(packing.digest, "documents"),
    "op5_piece_counts": _over(piece_counts.digest, "documents"),
    "op6_personal_data": _over(personal.digest, "documents"),
    "op7_toxicity": _over(toxicity.digest, "documents", "labels"),
    "op8_piece_lattice": _over(lattice.digest, "documents"),
    "op9_neighbour_tree": _over(neighbours.digest, "embeddings"),
    "op10_simhash": _over(simhash.digest, "documents"),
}

ORACLES = {
    "op1_substring_dedup": r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
win AS (SELECT doc_id, p, array_to_string(w[p:p + 34], ' ') AS s FROM d, unnest(range(1, len(w) - 33)) AS u(p)),
twice AS (SELECT s FROM win GROUP BY s HAVING count(*) > 1),
gone AS (SELECT DISTINCT doc_id, q FROM (SELECT doc_id, unnest(range(p, p + 35)) AS q FROM win WHERE s IN (SELECT s FROM twice))),
word AS (SELECT doc_id, q, w[q] AS x FROM d, unnest(range(1, len(w) + 1)) AS u(q)),
kept AS (SELECT word.doc_id, count(*) FILTER (gone.q IS NOT NULL) AS n_removed, string_agg(x, ' ' ORDER BY word.q) FILTER (gone.q IS NULL) AS k
         FROM word LEFT JOIN gone ON word.doc_id = gone.doc_id AND word.q = gone.q GROUP BY word.doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(k, '')) AS kept_sha256
FROM d LEFT JOIN kept USING (doc_id)
""",
}
