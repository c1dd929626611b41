"""One thin query per operator; each applies it to its whole table."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entlink.llm import exact_dedup, gif_media, hilbert_shards, piece_transducer, quality_ftrl, quote_threads, raking_mix, simhash_trie, token_store, warc_chain
from entlink.storage import bounded_batches, table


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    classes = simhash_trie.near_duplicate_classes(table(spark, sf_dir, "documents"))
    return classes.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def tokenizer_path(name: str) -> str:
    """Place of a public vocabulary file; ``ENTLINK_TOKENIZERS`` names another folder."""
    if folder := os.environ.get("ENTLINK_TOKENIZERS"):
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)


def op2_sentencepiece_wfst(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    found = piece_transducer.encode_documents(table(spark, sf_dir, "documents"), tokenizer_path("piece_bpe_32k.model"), with_ids=False)
    return found.select(F.col("id").alias("doc_id"), "n_pieces", "ids_crc32", "round_trip")


def op3_token_sstable(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    with open(tokenizer_path("byte_bpe_50k.json"), "rb") as f:
        vocabulary = spark.sparkContext.broadcast(f.read())
    manifest = token_store.write_tokens(table(spark, sf_dir, "documents"), lambda: token_store.bpe_encoder(vocabulary.value))
    return token_store.read_tokens(manifest, with_ids=False).select(F.col("id").alias("doc_id"), "start", "n_tokens", "ids_crc32")


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    docs = table(spark, sf_dir, "documents")
    weights = quality_ftrl.fit(docs, table(spark, sf_dir, "labels"))
    found = quality_ftrl.scored(docs, weights)
    return found.select(
        "doc_id",
        (F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3)) == 1).alias("held_out"),
        "score",
        (F.col("score") >= 0.5).cast("int").alias("predicted"),
    )


def op5_quote_threads(spark: SparkSession, sf_dir: str) -> DataFrame:
    threads = quote_threads.reply_ordered(table(spark, sf_dir, "conversations"))
    return threads.select(
        "conv_id", "turn", "role", "position", "parent_turn", "depth", "quoted_lines", F.sha2("clean_text", 256).alias("text_sha256")
    )


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.decisions(table(spark, sf_dir, "documents"), keep="largest")


def op7_hilbert_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = hilbert_shards.assign_shards(table(spark, sf_dir, "documents"), shards=16)
    return placed.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve"
    )


def op8_gif_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    found = gif_media.totals(gif_media.media_features(gif_media.store_media(table(spark, sf_dir, "documents"))))
    feature = F.format_string("%d frames, %d cs: %s", "frames", "duration", F.array_join("histogram", ","))
    return found.select(
        F.col("id").alias("doc_id"), "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", feature.alias("feature")
    )


def op9_warc_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    files = warc_chain.write_warc(table(spark, sf_dir, "pages"))
    found = warc_chain.read_warc(files, with_payload=False)
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op10_raking_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    bounded_batches(spark)
    return raking_mix.mixture(table(spark, sf_dir, "documents"), budget=0.5)


QUERIES = {
    "op1_simhash_near_dedup": op1_simhash_near_dedup,
    "op2_sentencepiece_wfst": op2_sentencepiece_wfst,
    "op3_token_sstable": op3_token_sstable,
    "op4_quality_classifier": op4_quality_classifier,
    "op5_quote_threads": op5_quote_threads,
    "op6_exact_dedup": op6_exact_dedup,
    "op7_hilbert_sharding": op7_hilbert_sharding,
    "op8_gif_media": op8_gif_media,
    "op9_warc_chain": op9_warc_chain,
    "op10_raking_mix": op10_raking_mix,
}

def _curve_sql(dims: int, bits: int) -> str:
    """DuckDB expression of the curve index of the list ``steps``: the walk over its transition tables."""
    nxt, digit = hilbert_shards.curve_tables(dims)
    table = str([n * (1 << dims) + d for n, d in zip(nxt, digit, strict=True)])
    quadrant = " + ".join(f"(((steps[{k + 1}] >> b) & 1) << {k})" for k in range(dims))
    walk = f"""list_reduce(list_transform(range({bits - 1}, -1, -1), lambda b: {quadrant}),
        lambda acc, q: [{table}[acc[1] * {1 << dims} + q + 1] >> {dims}, (acc[2] << {dims}) | ({table}[acc[1] * {1 << dims} + q + 1] % {1 << dims})], [0, 0])"""
    return walk.replace("lambda acc, q:", "lambda acc, q0:").replace("+ q +", "+ q0[1] +").replace(quadrant, f"[{quadrant}]") + "[2]"


#: Step of a value: the share of known values below it, times 32; null falls into the first step.
_STEP = lambda c: f"CASE WHEN {c} IS NULL THEN 0 ELSE ((rank() OVER (ORDER BY {c} NULLS LAST) - 1) * 32 // count({c}) OVER ()) END"

FOLD = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLES = {
    "op6_exact_dedup": f"""
        WITH d AS (SELECT doc_id, {FOLD} AS norm FROM documents)
        SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size,
               doc_id = max(doc_id) OVER g AS kept, sha256(norm) AS text_sha256
        FROM d WINDOW g AS (PARTITION BY norm)
    """,
    "op9_warc_chain": """
        WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
             g AS (SELECT page_id, html, strlen(html) AS n, min(page_id) OVER (PARTITION BY html) AS head FROM p)
        SELECT page_id, n::BIGINT AS payload_bytes, sha256(html) AS payload_digest,
               CASE WHEN n >= 100 AND page_id > head THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN n >= 100 AND page_id > head THEN head END AS refers_to
        FROM g
    """,
    # Exact steps by rank, the walk along the curve, then equal runs; crc32 byte by byte from its own table.
    "op7_hilbert_sharding": f"""
        WITH crc AS (SELECT list_transform(range(256), lambda n: list_reduce(range(8), lambda c, k: CASE WHEN c % 2 = 1 THEN xor(3988292384, c // 2) ELSE c // 2 END, n)) AS crc),
        d AS (SELECT doc_id, lang, source, strlen(coalesce(text, '')) + 1 AS size,
                     list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda x: ('0x' || x)::BIGINT) AS bytes FROM documents),
        s AS (SELECT doc_id, size::BIGINT AS size, xor(4294967295, list_reduce(bytes, lambda c, x: xor(c >> 8, crc[(xor(c, x) & 255) + 1]), 4294967295)) AS text_crc32,
                     [{_STEP('lang')}, {_STEP('source')}, {_STEP('size')}]::BIGINT[] AS steps FROM d, crc),
        c AS (SELECT doc_id, size, text_crc32, ({_curve_sql(3, 5)})::BIGINT AS curve FROM s),
        r AS (SELECT *, row_number() OVER (ORDER BY curve, doc_id NULLS FIRST, size, text_crc32) - 1 AS rank, count(*) OVER () AS total FROM c)
        SELECT doc_id, size, text_crc32, 'rows' AS law, (((rank + 1) * 16 - 1) // total)::INTEGER AS shard,
               (rank - (((rank + 1) * 16 - 1) // total) * total // 16)::BIGINT AS slot, NULL::INTEGER AS grown_shard, curve FROM r
    """,
    # The same rules in plain windows and a recursive walk from parent to parent.
    "op5_quote_threads": r"""
        WITH RECURSIVE m AS (
            SELECT row_number() OVER (ORDER BY conv_id NULLS FIRST, turn NULLS FIRST, role NULLS FIRST, coalesce(text, '')) AS msg,
                   conv_id, turn, role, coalesce(text, '') AS text FROM conversations),
        split AS (SELECT msg, conv_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS no FROM m),
        lines AS (SELECT *, len(regexp_replace(regexp_extract(line, '^(?:[ \t]?>)+'), '[^>]', '', 'g')) AS level,
                         regexp_matches(line, '^On .{1,200} wrote:[ \t]*$') AS intro FROM split),
        own AS (SELECT msg, conv_id, trim(regexp_replace(lower(line), '\s+', ' ', 'g')) AS unit FROM lines WHERE level = 0 AND NOT intro
                UNION SELECT msg, conv_id, trim(regexp_replace(lower(string_agg(line, chr(10) ORDER BY no)), '\s+', ' ', 'g'))
                FROM lines WHERE level = 0 AND NOT intro GROUP BY ALL),
        first_own AS (SELECT conv_id, unit, min(msg) AS origin FROM own WHERE unit <> '' GROUP BY ALL),
        step AS (SELECT *, CASE WHEN level = lag(level) OVER (PARTITION BY msg ORDER BY no) THEN 0 ELSE 1 END AS start FROM lines),
        quoted AS (SELECT *, sum(start) OVER (PARTITION BY msg ORDER BY no) AS run,
                          trim(regexp_replace(lower(regexp_replace(line, '^(?:[ \t]?>)+', '')), '\s+', ' ', 'g')) AS clean FROM step),
        units AS (SELECT msg, conv_id, level, clean AS unit FROM quoted WHERE level > 0
                  UNION ALL SELECT msg, conv_id, level, trim(regexp_replace(string_agg(clean, ' ' ORDER BY no), '\s+', ' ', 'g'))
                  FROM quoted WHERE level > 0 GROUP BY msg, conv_id, level, run),
        votes AS (SELECT u.msg, level, origin, count(*) AS n FROM units u JOIN first_own f
                  ON u.unit = f.unit AND u.conv_id IS NOT DISTINCT FROM f.conv_id WHERE origin < u.msg GROUP BY ALL),
        links AS (SELECT msg, origin AS parent FROM votes QUALIFY row_number() OVER (PARTITION BY msg ORDER BY level, n DESC, origin) = 1),
        walk AS (SELECT msg, parent AS root, 1 AS depth FROM links
                 UNION ALL SELECT w.msg, l.parent, depth + 1 FROM walk w JOIN links l ON w.root = l.msg),
        ends AS (SELECT msg, min(root) AS root, max(depth) AS depth FROM walk GROUP BY msg),
        clean AS (SELECT msg, count(*) FILTER (WHERE level > 0) AS quoted_lines,
                         regexp_replace(coalesce(string_agg(line, chr(10) ORDER BY no) FILTER (WHERE level = 0 AND NOT intro), ''), '^\n+|\n+$', '', 'g') AS kept
                  FROM lines GROUP BY msg)
        SELECT m.conv_id, m.turn, m.role,
               row_number() OVER (PARTITION BY m.conv_id ORDER BY coalesce(e.root, m.msg), coalesce(e.depth, 0), m.msg) - 1 AS position,
               p.turn AS parent_turn, coalesce(e.depth, 0)::BIGINT AS depth, c.quoted_lines::INTEGER AS quoted_lines,
               sha256(CASE WHEN c.quoted_lines > 0 THEN c.kept ELSE m.text END) AS text_sha256
        FROM m JOIN clean c USING (msg) LEFT JOIN ends e USING (msg) LEFT JOIN links l USING (msg) LEFT JOIN m p ON p.msg = l.parent
    """,
}
