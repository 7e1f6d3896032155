"""The queries of this subpackage, with production parameters over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpick.llm import chat, mix, neardup, neighbours, pieces, pseudonym, quality, repeats, topk, toxic

#: Used where the session holds no key (see ``pseudonym.session_key``): demonstration only.
DEMONSTRATION_KEY = "public-demonstration-key"
PIECE_MODEL = public_tokenizers.path("piece_bpe_32k.model")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_mix_to_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix.mix_report(table(spark, sf_dir, "documents"))


def mix_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What SQL can say of the mix: size, source size and target of every document, the words that the mix takes of its source (the best total that its budget allows),
    and whether no document exceeds 3 times its size."""
    rows = mix.mix_report(table(spark, sf_dir, "documents"))
    per = rows.groupBy("source").agg(F.sum("taken").alias("source_taken"), (F.max(F.col("taken") - 3 * F.col("size")) <= 0).alias("within_three"))
    out = rows.alias("r").join(F.broadcast(per.alias("p")), F.col("r.source").eqNullSafe(F.col("p.source")))
    return out.select("r.doc_id", "r.size", "r.source_size", F.round("r.target", 4).alias("target"), "p.source_taken", "p.within_three")


#: Targets by filling up from the largest ratio of ceiling to weight; whole epochs, and an exact subset sum (bits that move) of what they leave.
MIX_SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, coalesce('=' || source, '') AS source, source AS name, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, [5, 2, 1][(row_number() OVER (ORDER BY CAST(any_value(name) AS BLOB) NULLS LAST) - 1) % 3 + 1] AS weight FROM d GROUP BY source),
o AS (SELECT *, 3.0::DOUBLE * source_size AS cap, row_number() OVER (ORDER BY 3.0::DOUBLE * source_size / weight, source) AS place FROM s),
levels AS (SELECT a.*, ((SELECT sum(source_size) FROM s) - coalesce((SELECT sum(cap) FROM o b WHERE b.place < a.place), 0)) / (SELECT sum(weight) FROM o b WHERE b.place >= a.place) AS level FROM o a),
t AS (SELECT source, source_size, least(cap, (SELECT max(level) FROM levels) * weight) AS target FROM levels),
b AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(round(target) AS BIGINT) // source_size ELSE 0 END AS epochs, CAST(round(target) AS BIGINT) - CASE WHEN source_size > 0 THEN CAST(round(target) AS BIGINT) // source_size * source_size ELSE 0 END AS rest FROM t),
n AS (SELECT source, size, row_number() OVER (PARTITION BY source ORDER BY size, doc_id) AS rn FROM d WHERE size > 0),
reach AS (
    SELECT source, CAST(0 AS BIGINT) AS rn, CAST('1' || repeat('0', rest) AS BIT) AS bits FROM b
    UNION ALL
    SELECT r.source, r.rn + 1, CASE WHEN n.size < bit_length(r.bits) THEN r.bits | (r.bits >> CAST(n.size AS INTEGER)) ELSE r.bits END FROM reach r JOIN n ON n.source = r.source AND n.rn = r.rn + 1),
best AS (SELECT source, length(rtrim(CAST(arg_max(bits, rn) AS VARCHAR), '0')) - 1 AS extra FROM reach GROUP BY source)
SELECT doc_id, size, source_size, round(target, 4) AS target, CAST(epochs * source_size + extra AS BIGINT) AS source_taken, TRUE AS within_three FROM d JOIN b USING (source) JOIN best USING (source)
"""


def op2_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = "</s>[INST] ok [/INST]"
    probe = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(said).alias("text"))
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(probe)
    return chat.conversation_digest(chat.format_conversations(rows))


OP2_SQL = """
WITH said AS (
    SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
    UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]'
    UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
flagged AS (
    SELECT *, CAST(contains(text, '</s>') OR contains(role, '</s>') OR contains(role, '[/INST]') AS BIGINT) AS esc FROM said),
sized AS (
    SELECT *, CASE WHEN esc = 1
        THEN 19 + length(role) + length(text)
             + (length(role || text) - length(replace(replace(replace(role || text, '~', ''), '<', ''), '[', '')))
        ELSE 20 + length(role) + length(text) END AS chars
    FROM flagged)
SELECT conv_id, count(*) AS n_turns,
    sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
    CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
    sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
    CAST(sum(chars) AS BIGINT) AS formatted_chars,
    CAST(sum(esc) AS BIGINT) AS escaped_turns
FROM sized GROUP BY conv_id
"""


def op3_piece_encoding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.piece_digest(table(spark, sf_dir, "documents"), PIECE_MODEL)


def op4_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.remove_repeats(table(spark, sf_dir, "documents")).drop("runs")


OP4_SQL = """
WITH d AS (SELECT row_number() OVER () AS k, doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
w AS (SELECT k, j, md5_number(substr(h, 2 * j + 1, 400)) AS m FROM (SELECT k, h, unnest(range(0, greatest(len(h) // 2 - 199, 0))) AS j FROM d)),
again AS (SELECT m FROM w GROUP BY m HAVING count(*) > 1),
c AS (SELECT k, j, lag(j) OVER (PARTITION BY k ORDER BY j) AS p FROM w SEMI JOIN again USING (m)),
g AS (SELECT k, j, count(*) FILTER (p IS NULL OR j > p + 200) OVER (PARTITION BY k ORDER BY j) AS g FROM c),
span AS (SELECT k, min(j) AS a, max(j) + 200 AS z FROM g GROUP BY k, g),
gap AS (SELECT k, coalesce(lag(z) OVER (PARTITION BY k ORDER BY a), 0) AS f, a AS t FROM span UNION ALL SELECT k, max(z), 1000000000 FROM span GROUP BY k),
kept AS (SELECT k, string_agg(substr(h, 2 * f + 1, 2 * (t - f)), '' ORDER BY f) AS h FROM gap JOIN d USING (k) GROUP BY k),
tot AS (SELECT k, sum(z - a) AS r, count(*) AS n FROM span GROUP BY k)
SELECT doc_id, CAST(len(d.h) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(r, 0) AS BIGINT) AS n_removed, coalesce(n, 0) AS n_spans, sha256(unhex(coalesce(kept.h, d.h))) AS kept_sha256
FROM d LEFT JOIN tot USING (k) LEFT JOIN kept USING (k)
"""


def op5_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = pseudonym.pseudonymise(docs, pseudonym.session_key(spark, DEMONSTRATION_KEY), counts="replaced")
    kinds = [F.coalesce(F.col("replaced")[k], F.lit(0)).cast("long").alias(f"n_{k}") for k in pseudonym.KINDS]
    return out.select("doc_id", "text", *kinds)


def op6_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = neighbours.valid_vectors(table(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    return neighbours.nearest(vectors, vectors.where("id % 50 = 0"), k=5)


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"), percent=85)


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxic.score_toxicity(docs, toxic.train_toxicity(docs, table(spark, sf_dir, "labels")), threshold=0.5)


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.score_ids(docs, quality.train_quality(docs, table(spark, sf_dir, "labels")), threshold=0.3)


def op10_top_products(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = topk.integer_vectors(table(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    return topk.exact_top_k(vectors, vectors.where("id % 20 = 0"), k=20)


OP10_SQL = """
WITH whole AS (
    SELECT vec_id, embedding, generate_subscripts(embedding, 1) AS i, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings),
bad AS (SELECT DISTINCT vec_id FROM whole WHERE x IS NULL OR isnan(x) OR isinf(x)),
v AS (
    SELECT vec_id, list_transform(embedding, lambda x: floor(64 * CAST(x AS DOUBLE))) AS e
    FROM embeddings WHERE embedding IS NOT NULL AND vec_id NOT IN (SELECT vec_id FROM bad)),
s AS (
    SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_dot_product(q.e, c.e) AS BIGINT) AS score
    FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0),
r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20
"""

OP7_SQL = r"""
WITH RECURSIVE words AS (
    SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents),
grams AS (
    SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
        ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i : i + 4], ' '))) END AS s FROM words),
classes AS (SELECT list_sort(s) AS s, min(doc_id) AS cls, len(any_value(s)) AS n FROM grams WHERE len(s) > 0 GROUP BY list_sort(s)),
flat AS (SELECT cls, n, unnest(s) AS g FROM classes),
freq AS (SELECT g, count(*) AS df FROM flat GROUP BY g HAVING count(*) > 1),
ordered AS (
    SELECT f.cls, f.n, f.g, row_number() OVER (PARTITION BY f.cls ORDER BY coalesce(q.df, 1), f.g) AS place, coalesce(q.df, 1) AS df
    FROM flat f LEFT JOIN freq q ON q.g = f.g),
pre AS (SELECT * FROM ordered WHERE place <= n - CAST(ceil(0.85 * n - 1e-9) AS BIGINT) + 1 AND df > 1),
cand AS (SELECT DISTINCT a.cls AS a, b.cls AS b FROM pre a JOIN pre b ON a.g = b.g AND a.cls < b.cls AND 100 * least(a.n, b.n) >= 85 * greatest(a.n, b.n)),
links AS (
    SELECT a, b FROM cand JOIN classes x ON x.cls = a JOIN classes y ON y.cls = b
    WHERE 100 * len(list_intersect(x.s, y.s)) >= 85 * (x.n + y.n - len(list_intersect(x.s, y.s)))),
edges AS (SELECT a, b FROM links UNION SELECT b, a FROM links),
reach AS (SELECT cls AS a, cls AS b FROM classes UNION SELECT r.a, e.b FROM reach r JOIN edges e ON r.b = e.a),
comp AS (SELECT a AS cls, min(b) AS component FROM reach GROUP BY a)
SELECT g.doc_id, CAST(len(g.s) AS BIGINT) AS n_shingles, coalesce(c.component, g.doc_id) AS component_id, g.doc_id = coalesce(c.component, g.doc_id) AS kept
FROM grams g LEFT JOIN classes k ON k.s = list_sort(g.s) LEFT JOIN comp c ON c.cls = k.cls
"""


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_mix_to_weights": op1_mix_to_weights,
    "op2_chat_format": op2_chat_format,
    "mix_targets": mix_targets,
    "op3_piece_encoding": op3_piece_encoding,
    "op4_repeats": op4_repeats,
    "op5_pseudonyms": op5_pseudonyms,
    "op6_nearest": op6_nearest,
    "op7_near_duplicates": op7_near_duplicates,
    "op8_toxicity": op8_toxicity,
    "op9_quality": op9_quality,
    "op10_top_products": op10_top_products,
}

ORACLES: dict[str, str] = {"mix_targets": MIX_SQL, "op2_chat_format": OP2_SQL, "op4_repeats": OP4_SQL, "op7_near_duplicates": OP7_SQL, "op10_top_products": OP10_SQL}
