"""The registered queries of this package and their SQL, where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table
from .language_id import learn_and_identify
from .licenses import scan_licenses
from .near_dedup import near_duplicates
from .near_vectors import near_vectors
from .packing import pack_documents
from .pieces import encode_pieces
from .quality import learn_and_score
from .substring_dedup import remove_repeats
from .token_files import token_files
from .topk import top_products


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"), end_id=2).select("doc_id", "start", "n_tokens", "ids_crc32", "n_bytes")


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return remove_repeats(docs).select("doc_id", "n_words", "n_removed", "kept_sha256")


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return learn_and_identify(table(spark, sf_dir, "documents")).select("doc_id", "held_out", "lang_pred", "score")


def op4_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_products(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op5_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def op6_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


def op8_near_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings"))


#: Second rows of the planted table: every other component times this, by vec_id modulo 5 (cosines about 1, .97, .93, .91, .89).
PLANTED_FACTORS = (1.0, 1.6, 2.2, 2.6, 3.0)
PLANTED_FROM = 1_000_000_000


def planted_vectors(embeddings: DataFrame) -> DataFrame:
    """The table and, with other ids, a second row of each vector that stands at a cosine near 0.9 from it."""
    factor = F.element_at(F.array(*map(F.lit, PLANTED_FACTORS)), (F.pmod("vec_id", F.lit(5)) + 1).cast("int"))
    vector = F.col("embedding").cast("array<double>")
    turned = F.transform(vector, lambda x, i: F.when(i % 2 == 0, x * factor).otherwise(x))
    return embeddings.select("vec_id", vector.alias("embedding")).union(embeddings.select(F.col("vec_id") + PLANTED_FROM, turned))


def near_vectors_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op8 on a table that holds links; a higher recall than the default makes the SQL exact."""
    return near_vectors(planted_vectors(table(spark, sf_dir, "embeddings")), recall=0.9999)


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return learn_and_score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).select("doc_id", "held_out", "score", "predicted")


def op10_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Viterbi over the public model's pieces and scores."""
    return encode_pieces(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"), kind="unigram")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = {name: f for name, f in globals().items() if name.startswith("op") and callable(f)}
    return found | {"near_vectors_planted": near_vectors_planted}


_WORDS = r"regexp_extract_all({}, '[^\x20\x09-\x0D]+')"
_LOWER = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_REACH = "reach(id, c) AS (SELECT id, id FROM nodes UNION SELECT links.b, reach.c FROM reach JOIN links ON links.a = reach.id)"

OP2_SQL = f"""
WITH l AS (SELECT doc_id, {_WORDS.format("coalesce(text, '')")} AS l FROM documents),
w AS (SELECT doc_id, unnest(l) AS word, generate_subscripts(l, 1) AS pos, l FROM l),
s AS (SELECT doc_id, pos, word, CASE WHEN pos + 12 <= len(l) THEN array_to_string(l[pos:pos + 12], ' ') END AS s FROM w),
f AS (SELECT s, min(doc_id) AS least FROM s WHERE s IS NOT NULL GROUP BY 1),
m AS (SELECT doc_id, pos, word, max(CASE WHEN least < doc_id THEN pos END) OVER (PARTITION BY doc_id ORDER BY pos ROWS UNBOUNDED PRECEDING) AS last FROM s LEFT JOIN f USING (s)),
k AS (SELECT doc_id, pos, word, coalesce(last >= pos - 12, false) AS gone FROM m),
g AS (SELECT doc_id, count(*) AS n_words, sum(gone::INTEGER)::BIGINT AS n_removed, string_agg(word, ' ' ORDER BY pos) FILTER (NOT gone) AS kept FROM k GROUP BY 1)
SELECT doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM documents LEFT JOIN g USING (doc_id)
"""

OP4_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS q FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
p AS (SELECT a.vec_id AS query_id, b.vec_id, list_dot_product(a.q, b.q)::BIGINT AS score FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM p)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""

OP5_SQL = f"""
WITH RECURSIVE w AS (SELECT doc_id, {_WORDS.format("coalesce(" + _LOWER + ", '')")} AS l FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(l) >= 5 THEN list_transform(range(1, len(l) - 3), lambda i: array_to_string(l[i:i + 4], ' ')) WHEN len(l) > 0 THEN [array_to_string(l, ' ')] ELSE [] END) AS s FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 75 * (x.n + y.n - c)),
nodes AS (SELECT doc_id AS id FROM documents),
{_REACH}
SELECT id AS doc_id, coalesce(any_value(n), 0) AS n_shingles, min(c) AS component_id, id = min(c) AS kept FROM reach LEFT JOIN n ON n.doc_id = id GROUP BY id
"""

NEAR_VECTORS_SQL = f"""
WITH RECURSIVE {{given}}v AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM {{rows}} WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
u AS (SELECT vec_id, x, sqrt(list_dot_product(x, x)) AS n FROM v),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM u a JOIN u b ON a.vec_id <> b.vec_id AND a.n > 0 AND b.n > 0 WHERE list_dot_product(a.x, b.x) >= 0.9 * a.n * b.n),
nodes AS (SELECT vec_id AS id FROM {{rows}}),
d AS (SELECT a, count(*) AS n FROM links GROUP BY 1),
{_REACH}
SELECT id AS vec_id, coalesce(any_value(n), 0) AS n_links, min(c) AS component_id, id = min(c) AS kept FROM reach LEFT JOIN d ON d.a = id GROUP BY id
"""

OP8_SQL = NEAR_VECTORS_SQL.format(given="", rows="embeddings")
PLANTED_SQL = NEAR_VECTORS_SQL.format(
    given=f"""planted AS (SELECT vec_id, embedding::DOUBLE[] AS embedding FROM embeddings UNION ALL
SELECT vec_id + {PLANTED_FROM}, list_transform(embedding::DOUBLE[], lambda x, i: CASE WHEN i % 2 = 1 THEN x * {list(map(float, PLANTED_FACTORS))}[vec_id % 5 + 1] ELSE x END) FROM embeddings),
""",
    rows="planted",
)


def oracle_sql() -> dict[str, str]:
    return {"op2_substring_dedup": OP2_SQL, "op4_topk": OP4_SQL, "op5_near_dedup": OP5_SQL, "op8_near_vectors": OP8_SQL, "near_vectors_planted": PLANTED_SQL}
