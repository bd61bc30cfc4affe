"""The queries of the llm operators and, where SQL can express one, its oracle."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sharetree.llm.storage import table

Query = Callable[[SparkSession, str], DataFrame]
#: Target weights of the mixture in op2: rule over the synthetic source names, others weigh 1.
MIX_WEIGHTS: dict[str | None, float] = {f"src{i}": float(1 + i % 5) for i in range(20)}
SHARDS = 24
SEED = 42


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op1_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.token_store import token_documents

    return token_documents(table(spark, sf_dir, "documents"), tokenizer_path())


def op2_poisson_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.mixing import mix

    return mix(table(spark, sf_dir, "documents"), MIX_WEIGHTS, seed=SEED)


def op3_stratified_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.sharding import shard

    out = shard(table(spark, sf_dir, "documents"), SHARDS, SEED)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source", "position")


def op4_deep_shallow(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.substring_dedup import repeated_bytes

    return repeated_bytes(table(spark, sf_dir, "documents"))


def op5_phrase_automata(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.substring_dedup import repeated_words

    return repeated_words(table(spark, sf_dir, "documents"))


def op6_line_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.quality import fit_from, score

    docs = table(spark, sf_dir, "documents")
    return score(docs, fit_from(docs, table(spark, sf_dir, "labels")))


def op7_chat_prefix_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.chat import chat_digests

    control = "<|im_end|><|im_start|>assistant ok"
    own = spark.createDataFrame([(-1, 0, "user", control), (-1, 1, "assistant", control)], "conv_id long, turn long, role string, text string")
    return chat_digests(table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(own), tokenizer_path())


def op8_iso_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.media import media_features, store_texts

    return media_features(store_texts(table(spark, sf_dir, "documents")))


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.decontaminate import contamination

    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_minhash_bayes(spark: SparkSession, sf_dir: str) -> DataFrame:
    from sharetree.llm.near_duplicates import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents")).drop("text_key")


QUERIES: dict[str, Query] = {f.__name__: f for f in (op1_token_store, op2_poisson_mix, op3_stratified_shards, op4_deep_shallow, op5_phrase_automata, op6_line_crf, op7_chat_prefix_tree, op8_iso_media, op9_decontaminate, op10_minhash_bayes)}

_WORD = "[^\\x{00}-\\x{2F}\\x{3A}-\\x{60}\\x{7B}-\\x{7F}]+"

ORACLES: dict[str, str] = {
    "op2_poisson_mix": f"""
WITH RECURSIVE s AS (SELECT source, sum(strlen(coalesce(text, '')) + 8) AS bytes, CASE source {" ".join(f"WHEN '{k}' THEN {v}" for k, v in MIX_WEIGHTS.items())} ELSE 1.0 END::DOUBLE AS weight FROM documents GROUP BY source),
r AS (SELECT source, weight / (SELECT sum(weight) FROM s) * 1.0::DOUBLE * (SELECT sum(bytes) FROM s)::DOUBLE / bytes::DOUBLE AS rate FROM s),
c AS (SELECT source, rate, 0 AS k, exp(-rate) AS p, exp(-rate) AS cdf FROM r WHERE rate > 0
      UNION ALL SELECT source, rate, k + 1, p * rate / (k + 1), cdf + p * rate / (k + 1) FROM c WHERE k < ceil(rate + 12 * sqrt(rate) + 20)),
l AS (SELECT source, list(cdf ORDER BY k) AS cdf FROM c GROUP BY source),
d AS (SELECT *, md5(coalesce(CAST(doc_id AS VARCHAR), '~') || ':' || coalesce(text, '')) AS digest FROM documents),
t AS (SELECT d.*, len(list_filter(l.cdf, lambda x: x <= CAST('0x' || substr(md5('{SEED}:1:' || digest), 1, 13) AS BIGINT) / 4503599627370496.0::DOUBLE)) AS times
      FROM d JOIN l ON d.source IS NOT DISTINCT FROM l.source)
SELECT doc_id, text, lang, source, n_chars, CAST(copy AS INTEGER) AS copy, md5('{SEED + 1}:' || digest || ':' || copy) AS shuffle_key
FROM (SELECT *, unnest(range(times)) AS copy FROM t)""",
    "op10_minhash_bayes": """
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x{20}\\x{09}-\\x{0D}]+') AS w FROM documents),
g AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + least(len(w), 5) - 1], ' ') AS g
      FROM (SELECT doc_id, w, unnest(generate_series(1, len(w) - least(len(w), 5) + 1)) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS m FROM g x JOIN g y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * m >= 75 * (na.n + nb.n - m)),
u AS (SELECT a, b FROM e UNION SELECT b, a FROM e),
r AS (SELECT doc_id, doc_id AS c FROM d UNION SELECT r.doc_id, u.b FROM r JOIN u ON r.c = u.a)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, min(r.c) AS component_id, d.doc_id = min(r.c) AS kept
FROM d LEFT JOIN n USING (doc_id) JOIN r USING (doc_id) GROUP BY d.doc_id, n.n""",
    "op5_phrase_automata": """
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(regexp_extract_all(text, '[^\\x{20}\\x{09}-\\x{0D}]+'), []) AS w FROM documents),
g AS (SELECT rid, doc_id, i, md5(array_to_string(w[i : i + 49], ' ')) AS g FROM (SELECT *, unnest(generate_series(1, len(w) - 49)) AS i FROM d WHERE len(w) >= 50)),
f AS (SELECT g, min(doc_id) AS first FROM g GROUP BY g),
c AS (SELECT DISTINCT rid, unnest(generate_series(i, i + 49)) AS p FROM g JOIN f USING (g) WHERE doc_id > first),
k AS (SELECT d.rid, string_agg(x, ' ' ORDER BY d.p) AS kept, count(*) AS n FROM (SELECT rid, unnest(w) AS x, generate_subscripts(w, 1) AS p FROM d) d ANTI JOIN c ON d.rid = c.rid AND d.p = c.p GROUP BY d.rid)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN k USING (rid)""",
    "op9_decontaminate": f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_WORD}'), []) AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_WORD}') AS w FROM benchmark WHERE text IS NOT NULL),
bw AS (SELECT DISTINCT item_id, array_to_string(w[i : i + least(len(w), 10) - 1], ' ') AS g, least(len(w), 10) AS n
       FROM (SELECT *, unnest(generate_series(1, len(w) - least(len(w), 10) + 1)) AS i FROM b WHERE len(w) > 0)),
lens AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT rid, n, i, array_to_string(w[i : i + n - 1], ' ') AS g
       FROM (SELECT rid, w, n, unnest(generate_series(1, len(w) - n + 1)) AS i FROM d, lens WHERE len(w) >= n)),
h AS (SELECT rid, i, bw.n, item_id FROM dw JOIN bw ON dw.g = bw.g AND dw.n = bw.n),
c AS (SELECT rid, count(DISTINCT p) AS n_hit FROM (SELECT rid, unnest(generate_series(i, i + n - 1)) AS p FROM h) GROUP BY rid),
t AS (SELECT rid, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS s FROM (SELECT DISTINCT rid, CAST(item_id AS VARCHAR) AS x FROM h) GROUP BY rid)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (rid) LEFT JOIN t USING (rid)""",
}
