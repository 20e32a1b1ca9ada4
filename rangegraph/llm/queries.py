"""The registered queries of the corpus operators, with their SQL where SQL can express them."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chosen_path, exact_topk, importance, mixing, pieces, suffix_dedup, token_counts, toxicity, transport_stream, unit_dedup
from .common import table

MODEL = "piece_bpe_32k.model"


def op1_sentencepiece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode_digests(table(spark, sf_dir, "documents"), public_tokenizers.path(MODEL))


def op2_chosen_path_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chosen_path.link_classes(table(spark, sf_dir, "documents")).select("doc_id", "class_id", "n_links", "class_size")


def op3_importance_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return importance.resample(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_transport_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return transport_stream.read_media(transport_stream.write_media(table(spark, sf_dir, "documents")))


def op5_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = exact_topk.quantised(table(spark, sf_dir, "embeddings"))
    return exact_topk.search(vectors.where(F.pmod("vec_id", F.lit(50)) == 0), vectors, k=5)


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path(MODEL))


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.repeat_digests(table(spark, sf_dir, "documents"))


def op8_hierarchical_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.draw(table(spark, sf_dir, "documents"))


def op9_unit_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = unit_dedup.remove_units(table(spark, sf_dir, "documents"))
    kept = F.sha2(F.encode("text", "UTF-8"), 256).alias("kept_sha256")
    return cut.select("doc_id", "n_units", "n_removed", F.char_length("text").cast("long").alias("n_chars_kept"), kept, F.transform("removed", lambda s: s.start).alias("removed_start"), F.transform("removed", lambda s: s.end).alias("removed_end"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


QUERIES = {
    "op1_sentencepiece_codec": op1_sentencepiece_codec,
    "op2_chosen_path_join": op2_chosen_path_join,
    "op3_importance_resampling": op3_importance_resampling,
    "op4_transport_stream": op4_transport_stream,
    "op5_exact_topk": op5_exact_topk,
    "op6_token_counts": op6_token_counts,
    "op7_suffix_dedup": op7_suffix_dedup,
    "op8_hierarchical_mixing": op8_hierarchical_mixing,
    "op9_unit_dedup": op9_unit_dedup,
    "op10_toxicity": op10_toxicity,
}

ORACLES: dict[str, str] = {
    "op5_exact_topk": """
        WITH v AS (
          SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS w
          FROM embeddings
          WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
            AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0),
        s AS (
          SELECT q.vec_id AS query_id, c.vec_id,
                 CAST(list_sum(list_transform(list_zip(q.w, c.w), lambda p: p[1] * p[2])) AS BIGINT) AS score
          FROM v q JOIN v c ON c.vec_id <> q.vec_id WHERE q.vec_id % 50 = 0),
        r AS (
          SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
        SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
    """,
    "op9_unit_dedup": r"""
        WITH l0 AS (
          SELECT doc_id, generate_subscripts(p, 1) AS li, unnest(p) AS line
          FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS p FROM documents)),
        l AS (
          SELECT doc_id, li, line, string_split(regexp_replace(line, '([.!?]) ', '\1' || chr(1), 'g'), chr(1)) AS ss,
                 coalesce(sum(length(line) + 1) OVER (PARTITION BY doc_id ORDER BY li ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS a
          FROM l0),
        s0 AS (SELECT doc_id, li, a AS la, len(ss) AS ns, generate_subscripts(ss, 1) AS si, unnest(ss) AS unit FROM l),
        s AS (
          SELECT *, la + coalesce(sum(length(unit) + 1) OVER (PARTITION BY doc_id, li ORDER BY si ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS a FROM s0),
        u0 AS (
          SELECT doc_id, li, 0 AS si, a, line AS unit, 1 AS least FROM l
          UNION ALL SELECT doc_id, li, si, a, unit, 8 FROM s WHERE ns > 1),
        u1 AS (SELECT *, trim(regexp_replace(lower(unit), '\s+', ' ', 'g')) AS form FROM u0),
        u2 AS (SELECT * FROM u1 WHERE form <> '' AND length(form) - length(replace(form, ' ', '')) + 1 >= least),
        u AS (SELECT doc_id, li, si, (doc_id, a) > min((doc_id, a)) OVER (PARTITION BY form) AS again FROM u2),
        k AS (
          SELECT s.doc_id, s.li, s.si, s.a, s.unit, s.ns, NOT coalesce(ul.again, false) AND NOT (s.ns > 1 AND coalesce(us.again, false)) AS stays
          FROM s LEFT JOIN u ul ON ul.doc_id = s.doc_id AND ul.li = s.li AND ul.si = 0
          LEFT JOIN u us ON us.doc_id = s.doc_id AND us.li = s.li AND us.si = s.si),
        ln AS (
          SELECT doc_id, li, min(a) AS a, max(a + length(unit)) AS b, bool_or(stays) AS partly,
                 string_agg(unit, ' ' ORDER BY si) FILTER (stays) AS kept,
                 CASE WHEN bool_or(stays) THEN coalesce(list(struct_pack(a := CAST(a AS INTEGER), b := CAST(a + length(unit) AS INTEGER)) ORDER BY si) FILTER (NOT stays), [])
                      ELSE [struct_pack(a := CAST(min(a) AS INTEGER), b := CAST(max(a + length(unit)) AS INTEGER))] END AS gone
          FROM k GROUP BY doc_id, li)
        SELECT doc_id, CAST(count(*) AS INTEGER) AS n_units, CAST(sum(len(gone)) AS INTEGER) AS n_removed,
               length(coalesce(string_agg(kept, chr(10) ORDER BY li) FILTER (partly), '')) AS n_chars_kept,
               sha256(coalesce(string_agg(kept, chr(10) ORDER BY li) FILTER (partly), '')) AS kept_sha256,
               list_transform(flatten(list(gone ORDER BY li)), lambda g: g.a) AS removed_start,
               list_transform(flatten(list(gone ORDER BY li)), lambda g: g.b) AS removed_end
        FROM ln GROUP BY doc_id
    """,
    "op8_hierarchical_mixing": r"""
        WITH d AS (
          SELECT doc_id, lang, source,
                 CASE WHEN regexp_extract(coalesce(source, ''), '([0-9]+)$', 1) = '' THEN 'other'
                      ELSE list_extract(['web', 'books', 'code', 'forum'], CAST(regexp_extract(source, '([0-9]+)$', 1) AS BIGINT) % 4 + 1) END AS domain,
                 len(list_filter(regexp_split_to_array(coalesce(text, ''), '\s+'), lambda x: x <> '')) AS n_tokens
          FROM documents),
        leaf AS (SELECT domain, lang, source, sum(n_tokens) AS t, 2.0 * sum(n_tokens) AS c, 1.0 AS w FROM d GROUP BY ALL),
        lng AS (SELECT domain, lang, sum(c) AS c,
                       CASE lang WHEN 'en' THEN 0.5 WHEN 'de' THEN 0.2 WHEN 'fr' THEN 0.2 WHEN 'es' THEN 0.1 ELSE 1.0 END AS w FROM leaf GROUP BY ALL),
        dom AS (SELECT domain, sum(c) AS c,
                       CASE domain WHEN 'web' THEN 0.4 WHEN 'books' THEN 0.3 WHEN 'code' THEN 0.2 WHEN 'forum' THEN 0.1 ELSE 1.0 END AS w FROM lng GROUP BY domain),
        -- a level x fits a family if the children's min(capacity, weight * x) sum to what the family gets
        dx AS (SELECT x.domain, x.c / x.w AS x, sum(least(y.c, y.w * x.c / x.w)) AS g FROM dom x, dom y GROUP BY x.domain, x.c, x.w),
        db AS (
          SELECT domain, c, w, (SELECT 0.8 * sum(t) FROM leaf) AS b FROM dom),
        d1 AS (
          SELECT domain, least(c, w * ((b - (SELECT coalesce(sum(z.c), 0) FROM dom z JOIN dx ON dx.domain = z.domain WHERE dx.g <= b))
                                / nullif((SELECT sum(z.w) FROM dom z JOIN dx ON dx.domain = z.domain WHERE dx.g > b), 0))) AS part, c,
                 (SELECT g FROM dx WHERE dx.domain = db.domain) <= b AS isfull FROM db),
        d2 AS (SELECT domain, CASE WHEN isfull THEN c ELSE part END AS b FROM d1),
        lx AS (SELECT x.domain, x.lang, sum(least(y.c, y.w * x.c / x.w)) AS g FROM lng x JOIN lng y USING (domain) GROUP BY x.domain, x.lang, x.c, x.w),
        l0 AS (SELECT lng.*, lx.g, d2.b FROM lng JOIN lx USING (domain, lang) JOIN d2 USING (domain)),
        l1 AS (
          SELECT domain, lang, CASE WHEN g <= b THEN c ELSE w * (b - coalesce(sum(c) FILTER (g <= b) OVER (PARTITION BY domain), 0)) / sum(w) FILTER (g > b) OVER (PARTITION BY domain) END AS b FROM l0),
        sx AS (SELECT x.domain, x.lang, x.source, sum(least(y.c, y.w * x.c / x.w)) AS g FROM leaf x JOIN leaf y USING (domain, lang) GROUP BY x.domain, x.lang, x.source, x.c, x.w),
        s0 AS (SELECT leaf.*, sx.g, l1.b FROM leaf JOIN sx USING (domain, lang, source) JOIN l1 USING (domain, lang)),
        s1 AS (
          SELECT domain, lang, source, t, CAST(floor(CASE WHEN g <= b THEN c ELSE w * (b - coalesce(sum(c) FILTER (g <= b) OVER (PARTITION BY domain, lang), 0)) / sum(w) FILTER (g > b) OVER (PARTITION BY domain, lang) END + 1e-6) AS BIGINT) AS b FROM s0),
        s2 AS (SELECT *, least(CASE WHEN t > 0 THEN b // t ELSE 0 END, 2) AS e FROM s1),
        s3 AS (SELECT *, CASE WHEN e < 2 THEN b - e * t ELSE 0 END AS r FROM s2),
        j AS (SELECT d.*, s3.e, s3.r FROM d JOIN s3 USING (domain, lang, source)),
        p AS (SELECT *, sum(n_tokens) OVER (PARTITION BY domain, lang, source ORDER BY md5('7:' || e || ':' || doc_id) ROWS UNBOUNDED PRECEDING) AS s FROM j)
        SELECT doc_id, domain, lang, source, CAST(n_tokens AS BIGINT) AS n_tokens, CAST(x AS INTEGER) AS epoch FROM (SELECT *, unnest(range(0, CAST(e AS BIGINT))) AS x FROM j)
        UNION ALL
        SELECT doc_id, domain, lang, source, CAST(n_tokens AS BIGINT) AS n_tokens, CAST(e AS INTEGER) AS epoch FROM p WHERE r > 0 AND s <= r
    """,
}
