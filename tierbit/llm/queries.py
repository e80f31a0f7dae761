"""The operators applied to the given tables, with the columns their contracts name."""

from __future__ import annotations

from pyspark.sql import functions as F

from tierbit.llm import exactdedup, langid, mixing, neardup, packing, pii, shard, tokenio, topk, toxicity
from tierbit.llm.common import id_crc, table, text_crc


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_sharding(spark, sf_dir):
    out = shard.shuffle_into_shards(table(spark, sf_dir, "documents").select("doc_id", "text"), n_shards=8)
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + 1
    return out.select("doc_id", size.alias("size"), text_crc().alias("text_crc32"), F.lit("rows").alias("law"), F.col("shard").cast("int").alias("shard"), "slot", F.lit(None).cast("int").alias("grown_shard"))


def op2_topk(spark, sf_dir):
    return topk.threshold_topk(table(spark, sf_dir, "embeddings"), F.col("id") % 100 == 0, k=10)


def op3_language(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held = F.coalesce(id_crc() % 3 == 1, F.lit(False))
    model = langid.fit(docs, ~held)
    return langid.identify(docs.select("doc_id", "text"), model).select("doc_id", held.alias("held_out"), "lang_pred", "score")


def op4_neardup(spark, sf_dir):
    return neardup.near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("tag")


def op5_pii(spark, sf_dir):
    out = pii.find_pii(table(spark, sf_dir, "documents").select("doc_id", "text"))
    count = lambda k: F.size(F.filter("base", lambda x: x["kind"] == k)).cast("long")
    return out.select("doc_id", *[count(i).alias(f"n_{k}") for i, k in enumerate(pii.KINDS)], F.sha2(pii.spelled(F.col("base")).cast("binary"), 256).alias("base_sha256"), pii.spelled(F.sort_array(F.concat("base", "added"))).alias("spans"))


def op6_tokens(spark, sf_dir):
    manifest = tokenio.write_tokens(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"), end_id=2)
    return tokenio.read_tokens(spark, manifest).select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))


def op7_packing(spark, sf_dir):
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"), end_id=1, window=2048)


def op8_mixing(spark, sf_dir):
    out = mixing.mixed(table(spark, sf_dir, "documents").select("doc_id", "text", "source", "lang"))
    return out.select("doc_id", "source", "lang", "topic", "tokens", F.round("factor", 6).alias("factor"), F.round("prob", 6).alias("prob"), "copies")


def op9_exactdedup(spark, sf_dir):
    return exactdedup.exact_dedup(table(spark, sf_dir, "documents").select("doc_id", "text"), keep="largest").drop("tag")


def op10_toxicity(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    held = F.coalesce(id_crc() % 4 == 2, F.lit(False))
    scorer = toxicity.fit(docs, table(spark, sf_dir, "labels"), ~held)
    out = toxicity.score(docs, scorer)
    return out.select("doc_id", held.alias("held_out"), "score", F.when(F.col("score") >= 0.3, 1).otherwise(0).alias("predicted"))


def queries():
    return {f.__name__: f for f in (op1_sharding, op2_topk, op3_language, op4_neardup, op5_pii, op6_tokens, op7_packing, op8_mixing, op9_exactdedup, op10_toxicity)}


def _raking_sql(rounds: int = 30) -> str:
    """The mixing operator unrolled: three scalings a round over the cell table."""
    ctes = ["""d AS MATERIALIZED (SELECT doc_id, coalesce(source, '<null>') AS source, coalesce(lang, '<null>') AS lang,
 CASE WHEN contains(t, 'License') THEN 'legal' WHEN contains(t, ' = ') THEN 'code' WHEN contains(t, ' | ') THEN 'table' WHEN length(t) >= 4000 THEN 'long' ELSE 'prose' END AS topic,
 CAST(floor(length(t) / 4) + 1 AS BIGINT) AS tokens FROM (SELECT *, coalesce(text, '') AS t FROM documents))""",
            "c AS MATERIALIZED (SELECT source, lang, topic, CAST(sum(tokens) AS DOUBLE) AS tokens FROM d GROUP BY ALL)",
            "a AS MATERIALIZED (SELECT sum(tokens) AS total FROM c)",
            "w0 AS MATERIALIZED (SELECT source, lang, topic, tokens, tokens / total AS w FROM c, a)"]
    for dim, power in mixing.Mix().powers.items():
        ctes.append(f"p_{dim} AS MATERIALIZED (SELECT {dim}, pow(sum(w), {power}) AS g FROM w0 GROUP BY {dim})")
        ctes.append(f"g_{dim} AS MATERIALIZED (SELECT {dim}, g / (SELECT sum(g) FROM p_{dim}) AS goal FROM p_{dim})")
    n = 0
    for _ in range(rounds):
        for dim in mixing.DIMS:
            ctes.append(f"w{n + 1} AS MATERIALIZED (SELECT source, lang, topic, tokens, w * goal / sum(w) OVER (PARTITION BY {dim}) AS w FROM w{n} JOIN g_{dim} USING ({dim}))")
            n += 1
    ctes.append(f"f AS MATERIALIZED (SELECT source, lang, topic, tokens, w * total / tokens AS factor FROM w{n}, a)")
    # c solves sum(tokens * least(1, c * factor)) = budget: on the right set of cut cells it is a ratio
    ctes.append("o AS (SELECT factor, tokens, sum(tokens) OVER big AS cut_t, sum(tokens * factor) OVER rest AS free_m FROM f WINDOW big AS (ORDER BY factor DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), rest AS (ORDER BY factor DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))")
    ctes.append(f"s AS MATERIALIZED (SELECT ({mixing.Mix().budget} * total - coalesce(cut_t, 0)) / free_m AS c FROM o, a WHERE ({mixing.Mix().budget} * total - coalesce(cut_t, 0)) / free_m * factor <= 1 ORDER BY factor DESC LIMIT 1)")
    return f"""WITH {", ".join(ctes)}, r AS (SELECT doc_id, source, lang, topic, d.tokens, factor, least(1.0, factor * s.c) AS p,
 CAST(CAST('0x' || substr(md5('{mixing.Mix().seed}:' || coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 8) AS BIGINT) AS DOUBLE) / 4294967296.0 AS u FROM d JOIN f USING (source, lang, topic), s)
SELECT doc_id, source, lang, topic, tokens, round(factor, 6) AS factor, round(p, 6) AS prob, CAST(floor(p) + CASE WHEN u < p - floor(p) THEN 1 ELSE 0 END AS BIGINT) AS copies FROM r"""


def oracle_sql():
    dot = "list_sum(list_transform(list_zip(a.v, b.v), lambda x: x[1] * x[2]))"
    return {
        "op2_topk": f"""WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 1024) AS BIGINT)) AS v FROM embeddings
 WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0),
s AS (SELECT a.vec_id AS query_id, b.vec_id, CAST({dot} AS BIGINT) AS score FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE a.vec_id % 100 = 0)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 10""",
        "op8_mixing": _raking_sql(),
        "op9_exactdedup": """SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id IS NOT DISTINCT FROM max(doc_id) OVER w AS kept, sha256(coalesce(text, '')) AS text_sha256
 FROM documents WINDOW w AS (PARTITION BY coalesce(text, ''))""",
    }
