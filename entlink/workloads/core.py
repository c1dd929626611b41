"""Queries of the linking methods, with the DuckDB statements that must give the same rows."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from entlink.ann import signs
from entlink.ann.exact import exact_knn, grouped_knn
from entlink.functions.text import h, hashed_bag, tokens
from entlink.functions.vectors import cosine_distance, elu
from entlink.operators import candidates as cand
from entlink.operators import evaluate, loss, rank, vectorize
from entlink.registry import query
from entlink.sources import mentions as src
from entlink.storage import materialize, measured_broadcasts, table

DIM = 128

# ---- SQL fragments shared by the statements below (DuckDB) ----
H = lambda x: f"('0x' || substr(md5({x}), 1, 8))::BIGINT"
TOK = lambda x: f"list_filter(regexp_split_to_array(lower(coalesce({x}, '')), '[^\\p{{L}}\\p{{N}}]+'), lambda t: t <> '')"
_swap = lambda w, pairs: f"CASE {w} " + " ".join(f"WHEN '{a}' THEN '{b}'" for a, b in pairs.items()) + f" ELSE {w} END"
MENTIONS = f"""
    m0 AS (SELECT p.*, i, p_partkey || '#' || i AS seed FROM part p, range(3) r(i)),
    m1 AS (SELECT *, CASE WHEN {H("'c' || seed")} % 10 < 6 THEN 'clean' WHEN {H("'c' || seed")} % 10 = 6 THEN 'homonym'
                          WHEN {H("'c' || seed")} % 10 = 7 THEN 'hyponym' WHEN {H("'c' || seed")} % 10 = 8 THEN 'synonym' ELSE 'misspelling' END AS channel,
                  split_part(p_name, ' ', 1) AS w1, split_part(p_name, ' ', -1) AS w2, ({H("'m' || seed")} % length(p_name))::INT AS cut FROM m0),
    m2 AS (SELECT *, CASE channel WHEN 'hyponym' THEN w1 || ' ' || ({_swap("w2", src.BROADER)}) WHEN 'synonym' THEN ({_swap("w1", src.ALIKE)}) || ' ' || w2
                          WHEN 'misspelling' THEN substr(p_name, 1, cut) || substr(p_name, cut + 2) ELSE p_name END AS said FROM m1),
    mentions AS (SELECT seed AS mention_id, p_partkey::VARCHAR AS tuple_id, p_name AS instance_id, channel,
        CASE WHEN channel = 'homonym' THEN 'Someone asked about the ' || said || '.'
             WHEN {H("'t' || seed")} % 4 = 0 THEN 'The ' || said || ' from ' || p_brand || ' comes in size ' || p_size || ' and belongs to the ' || lower(p_type) || ' line.'
             WHEN {H("'t' || seed")} % 4 = 1 THEN 'In size ' || p_size || ', ' || p_brand || ' sells a ' || said || '.'
             WHEN {H("'t' || seed")} % 4 = 2 THEN 'Among ' || lower(p_type) || ' goods the ' || said || ' is the pride of ' || p_brand || '.'
             ELSE 'Our shop keeps a ' || said || '. It has size ' || p_size || ' and was made by ' || p_brand || '.' END AS text FROM m2),
    split AS (SELECT *, CASE WHEN {H("'u' || instance_id")} % 5 = 0 THEN 'unseen' WHEN {H("'t' || mention_id")} % 5 = 0 THEN 'test' ELSE 'train' END AS split FROM mentions),
    tuples AS (SELECT p_partkey::VARCHAR AS tuple_id, p_name AS instance_id, concat_ws(' ', p_name, p_brand, lower(p_type), 'size ' || p_size) AS text FROM part)
"""


def part_mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return src.verbalized(table(spark, sf_dir, "part"))


@query("q01_profile_entity_types", f"""WITH {MENTIONS},
    f AS (SELECT p_name, ((p_brand IS NOT NULL)::INT + (p_type IS NOT NULL)::INT + (p_size IS NOT NULL)::INT + (p_retailprice IS NOT NULL)::INT) / 4.0 AS d FROM part),
    n AS (SELECT count(*) AS s FROM mentions)
    SELECT 'product-name' AS entity_type, count(DISTINCT p_name) AS instances, count(*) AS tuples, any_value(s) AS sentences,
           round(any_value(s) / count(DISTINCT p_name), 6) AS per_instance, 4 AS columns, round(avg(d), 6)::DOUBLE AS density FROM f, n
    UNION ALL
    SELECT 'dialogue', count(DISTINCT conv_id), count(*) FILTER (WHERE turn = 0), count(*) FILTER (WHERE turn > 0),
           round(count(*) FILTER (WHERE turn > 0) / count(DISTINCT conv_id) FILTER (WHERE turn = 0), 6), 1, 1.0 FROM conversations""")
def profile_types(spark, sf_dir):
    part = table(spark, sf_dir, "part")
    a = evaluate.profile(part, ["p_brand", "p_type", "p_size", "p_retailprice"], "p_name", part_mentions(spark, sf_dir))
    tuples, mentions = src.entity_type(spark, sf_dir, "dialogue")
    b = evaluate.profile(tuples, ["text"], "instance_id", mentions)
    return a.select(F.lit("product-name").alias("entity_type"), "*").unionByName(b.select(F.lit("dialogue").alias("entity_type"), "*"))


@query("q02_split_counts", f"WITH {MENTIONS} SELECT split, channel, count(*) AS n FROM split GROUP BY ALL")
def split_counts(spark, sf_dir):
    return src.with_split(part_mentions(spark, sf_dir)).groupBy("split", "channel").agg(F.count("*").alias("n"))


@query("q03_verbalized_mentions", f"WITH {MENTIONS} SELECT * FROM mentions")
def verbalized_mentions(spark, sf_dir):
    return part_mentions(spark, sf_dir)


@query("q04_sentence_split", r"""WITH p AS (SELECT doc_id, unnest(regexp_split_to_array(regexp_replace(text, '([.!?])([ \t\r\f\v])', '\1' || chr(2) || '\2', 'g'), chr(2) || '|\n')) AS s FROM documents)
    SELECT doc_id, s AS text, count(*) AS n FROM p WHERE trim(s, ' ') <> '' GROUP BY ALL""")
def sentence_split(spark, sf_dir):
    return src.sentences(table(spark, sf_dir, "documents")).groupBy("doc_id", "text").agg(F.count("*").alias("n"))


@query("q05_token_spans", f"SELECT token, count(*) AS n, count(DISTINCT item_id) AS items FROM (SELECT item_id, unnest({TOK('text')}) AS token FROM benchmark) GROUP BY token")
def token_spans(spark, sf_dir):
    rows = table(spark, sf_dir, "benchmark").select("item_id", F.posexplode(tokens(F.col("text"))).alias("no", "token"))
    return rows.groupBy("token").agg(F.count("*").alias("n"), F.countDistinct("item_id").alias("items"))


@query("q06_normalize_numeric", """SELECT p_partkey, round((p_size - avg(p_size) OVER ()) / stddev_pop(p_size) OVER (), 6) AS p_size_z,
    round((p_retailprice - avg(p_retailprice) OVER ()) / stddev_pop(p_retailprice) OVER (), 6) AS p_retailprice_z FROM part""")
def normalize_numeric(spark, sf_dir):
    out = vectorize.normalized(table(spark, sf_dir, "part"), ["p_size", "p_retailprice"])
    return out.select("p_partkey", F.round("p_size_z", 6).alias("p_size_z"), F.round("p_retailprice_z", 6).alias("p_retailprice_z"))


@query("q07_one_hot_long", """WITH d AS (SELECT v, row_number() OVER (ORDER BY v) AS place FROM (SELECT DISTINCT o_orderpriority AS v FROM orders))
    SELECT o_orderkey, place::INT AS place FROM orders JOIN d ON o_orderpriority = v""")
def one_hot_long(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    hot = vectorize.one_hot(F.col("o_orderpriority"), vectorize.domain(orders, "o_orderpriority"))
    return orders.select("o_orderkey", F.posexplode(hot).alias("i", "bit")).where("bit = 1").select("o_orderkey", (F.col("i") + 1).alias("place"))


HASHED = lambda rel, key, text, dim: f"""(SELECT id, bucket, raw / sqrt(sum(raw * raw) OVER (PARTITION BY id)) AS value FROM
    (SELECT id, ({H('token')} % {dim})::INT AS bucket, sum(CASE WHEN ('0x' || substr(md5(token), 9, 8))::BIGINT % 2 = 0 THEN 1 ELSE -1 END) AS raw
     FROM (SELECT {key} AS id, unnest({TOK(text)}) AS token FROM {rel}) GROUP BY ALL HAVING raw <> 0))"""  # noqa: E731


@query("q08_hash_encoder_long", f"SELECT id, bucket, round(value, 6) AS value FROM {HASHED('documents', 'doc_id', 'text', DIM)}")
def hash_encoder_long(spark, sf_dir):
    return vectorize.hashed_long(table(spark, sf_dir, "documents"), "doc_id", "text", DIM).withColumn("value", F.round("value", 6))


@query("q09_tfidf_long", f"""WITH c AS (SELECT item_id AS id, token, count(*) AS tf FROM (SELECT item_id, unnest({TOK('text')}) AS token FROM benchmark) GROUP BY ALL),
    d AS (SELECT token, count(*) AS df FROM c GROUP BY token HAVING count(*) >= 2)
    SELECT id, token, round(tf * ln((SELECT count(*) FROM benchmark) / df), 6) AS weight FROM c JOIN d USING (token)""")
def tfidf(spark, sf_dir):
    return vectorize.tfidf_long(table(spark, sf_dir, "benchmark"), "item_id", "text").withColumn("weight", F.round("weight", 6))


@query("q10_fk_sum_vector_long", """WITH v AS (SELECT l_orderkey, sum(l_quantity) AS e0, sum(l_extendedprice) AS e1, sum(l_discount) AS e2 FROM lineitem GROUP BY 1)
    SELECT o_orderkey, round(coalesce(e0, 0), 4) AS e0, round(coalesce(e1, 0), 2) AS e1, round(coalesce(e2, 0), 4) AS e2 FROM orders LEFT JOIN v ON o_orderkey = l_orderkey""")
def fk_sum(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", F.array("l_quantity", "l_extendedprice", "l_discount").alias("vec"))
    out = vectorize.fk_vector(table(spark, sf_dir, "orders"), "o_orderkey", lines, "l_orderkey", "vec", 3, "v_fk")
    return out.select("o_orderkey", *[F.round(F.element_at("v_fk", i + 1), d).alias(f"e{i}") for i, d in enumerate((4, 2, 4))])


@query("q11_signature_long", f"""WITH t AS (SELECT id, bucket, value FROM {HASHED('customer', 'c_custkey', 'c_name', 32)}),
    n AS (SELECT id, bucket, value FROM {HASHED('nation', 'n_nationkey', 'n_name', 32)}), g AS (SELECT id, bucket, value FROM {HASHED('region', 'r_regionkey', 'r_name', 32)}),
    d AS (SELECT v, row_number() OVER (ORDER BY v) - 1 AS place FROM (SELECT DISTINCT c_mktsegment AS v FROM customer)),
    s AS (SELECT id AS key, bucket AS i, value FROM t
      UNION ALL SELECT c_custkey, 32, (c_acctbal - avg(c_acctbal) OVER ()) / stddev_pop(c_acctbal) OVER () FROM customer
      UNION ALL SELECT c_custkey, 33 + place, 1.0 FROM customer JOIN d ON c_mktsegment = v
      UNION ALL SELECT c_custkey, 33 + (SELECT count(*) FROM d) + bucket, value FROM customer JOIN n ON c_nationkey = id
      UNION ALL SELECT c_custkey, 65 + (SELECT count(*) FROM d) + bucket, value FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN g ON n_regionkey = g.id)
    SELECT key, i::INT AS i, round(value, 6) AS value FROM s WHERE round(value, 6) <> 0""")
def signature_long(spark, sf_dir):
    from entlink.spec import CUSTOMER

    tables = {n: table(spark, sf_dir, n) for n in ("customer", "nation", "region")}
    sig, _ = vectorize.signature(tables, CUSTOMER, text_dim=32)
    return sig.select("key", F.posexplode("v_r").alias("i", "value")).withColumn("value", F.round("value", 6)).where("value != 0")


def vectors(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))


def _knn_sql(distance: str) -> str:
    return f"""WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings),
        d AS (SELECT q.vec_id AS query_id, b.vec_id AS result_id, {distance} AS distance FROM e q, e b)
        SELECT query_id, result_id, round(distance, 6) AS distance, row_number() OVER (PARTITION BY query_id ORDER BY distance, result_id)::INT AS rank
        FROM d QUALIFY rank <= 10"""


@query("q12_exact_knn_cosine", _knn_sql("CASE WHEN q.vec_id = b.vec_id THEN -1 ELSE 1 - list_inner_product(q.v, b.v) / sqrt(list_inner_product(q.v, q.v) * list_inner_product(b.v, b.v)) END").replace("round(distance, 6)", "round(greatest(distance, 0), 6)"))
def knn_cosine(spark, sf_dir):
    found = exact_knn(vectors(spark, sf_dir), vectors(spark, sf_dir), 10)
    return found.select("query_id", "result_id", (F.round(F.greatest("distance", F.lit(0.0)), 6) + 0.0).alias("distance"), "rank")


@query("q13_exact_knn_euclid", _knn_sql("list_distance(q.v, b.v)"))
def knn_euclid(spark, sf_dir):
    found = exact_knn(vectors(spark, sf_dir), vectors(spark, sf_dir), 10, "euclidean")
    own = F.col("query_id") == F.col("result_id")  # a matrix product leaves rounding noise on the diagonal
    return found.select("query_id", "result_id", F.when(own, 0.0).otherwise(F.round("distance", 6)).alias("distance"), "rank")


def _bag(text):
    """Signed integer counts, so that distances are the same to the last bit in every engine."""
    @F.pandas_udf("array<double>")
    def run(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: hashed_bag(t, DIM))

    return run(text)


def nearest_to_texts(spark: SparkSession, sf_dir: str, n: int = 10) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Top mentions of every text of part tuples in each split by hashed bags, without learning; with the tuples that have a text alike, and the splits.

    Gives (split, text, result_id, distance, rank, found, channel), then (split, text, tuple_id, n, asked): the least of
    the ``n`` tuples of one text and instance, and (split, instance_id).

    Equal texts have equal vectors, so every text is compared once.  The nearest ``n`` texts, ordered by distance and
    least mention id, hold all of the nearest ``n`` mentions; of one text only the first ``n`` mentions can be among them.
    """
    tuples, mentions = src.entity_type(spark, sf_dir, "product-name")
    measured_broadcasts(spark)
    marked = src.with_split(mentions)
    pools = marked.select("split", "instance_id").distinct()
    alike = tuples.groupBy("text", "instance_id").agg(F.min("tuple_id").alias("tuple_id"), F.count("*").alias("n"))
    asked = materialize(alike.join(pools, "instance_id").select("split", "text", "tuple_id", "n", F.col("instance_id").alias("asked")), "raw-asked")
    first = F.row_number().over(Window.partitionBy("split", "text").orderBy("mention_id"))
    members = marked.withColumn("turn", first).where(F.col("turn") <= n)
    members = materialize(members.select("split", "text", "turn", F.col("mention_id").alias("result_id"), F.col("instance_id").alias("found"), "channel"), "raw-members")
    unit = lambda key: (F.col("split").alias("grp"), F.col(key).alias("id"), _bag(F.col("text")).alias("vec"))
    said = asked.groupBy("split", "text").agg(F.min("tuple_id").alias("q_id"))
    near = grouped_knn(said.select(*unit("q_id")), members.where("turn = 1").select(*unit("result_id")), n)
    near = near.select(F.col("grp").alias("split"), F.col("query_id").alias("q_id"), F.col("result_id").alias("b_id"), "distance")
    heads = members.where("turn = 1").select("split", "text", F.col("result_id").alias("b_id"))
    rows = near.join(heads, ["split", "b_id"]).join(members, ["split", "text"]).select("split", "q_id", "distance", "result_id", "found", "channel")
    w = Window.partitionBy("split", "q_id").orderBy("distance", "result_id")
    best = rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n)
    return materialize(best.join(said, ["split", "q_id"]).drop("q_id"), "raw-links"), asked, pools


def raw_links(spark: SparkSession, sf_dir: str, n: int = 10) -> DataFrame:
    """Top mentions of every part tuple in each split, one row for each."""
    best, _, pools = nearest_to_texts(spark, sf_dir, n)
    tuples, _ = src.entity_type(spark, sf_dir, "product-name")
    asked = tuples.join(pools, "instance_id").select("split", "text", "tuple_id", F.col("instance_id").alias("asked"))
    out = best.join(asked, ["split", "text"]).select("split", F.col("tuple_id").alias("query_id"), "result_id", "distance", "rank", "asked", "found", "channel")
    return out.withColumn("correct", F.col("asked") == F.col("found"))


RAW_LINKS = f"""{MENTIONS},
    units AS (SELECT 'r' || tuple_id AS uid, text FROM tuples UNION ALL SELECT 'm' || mention_id, text FROM split),
    cells AS (SELECT uid, ({H('token')} % {DIM})::INT AS bucket, sum(CASE WHEN ('0x' || substr(md5(token), 9, 8))::BIGINT % 2 = 0 THEN 1 ELSE -1 END) AS raw
              FROM (SELECT uid, unnest({TOK('text')}) AS token FROM units) GROUP BY ALL),
    grid AS (SELECT uid, list(coalesce(raw, 0)::DOUBLE ORDER BY g.bucket) AS v FROM (SELECT uid, b AS bucket FROM (SELECT DISTINCT uid FROM cells), range({DIM}) r(b)) g LEFT JOIN cells USING (uid, bucket) GROUP BY uid),
    qs AS (SELECT DISTINCT t.tuple_id, t.instance_id, s.split FROM tuples t JOIN split s USING (instance_id)),
    d AS (SELECT q.tuple_id AS query_id, s.mention_id AS result_id, q.split, q.instance_id = s.instance_id AS correct, s.channel,
                 1 - list_inner_product(a.v, b.v) / sqrt(list_inner_product(a.v, a.v) * list_inner_product(b.v, b.v)) AS distance
          FROM qs q JOIN split s USING (split) JOIN grid a ON a.uid = 'r' || q.tuple_id JOIN grid b ON b.uid = 'm' || s.mention_id),
    links AS (SELECT *, row_number() OVER (PARTITION BY split, query_id ORDER BY distance, result_id) AS rank FROM d QUALIFY rank <= 10)"""


@query("q14_hit_at_k_raw", f"""WITH {RAW_LINKS},
    best AS (SELECT split, query_id, min(rank) FILTER (WHERE correct) AS best FROM links GROUP BY ALL)
    SELECT split, k::INT AS k, count(*) FILTER (WHERE best <= k) AS hits, count(*) AS queries, round(count(*) FILTER (WHERE best <= k) / count(*), 6) AS rate
    FROM best, (VALUES (1), (5), (10)) t(k) GROUP BY split, k""")
def hit_at_k_raw(spark, sf_dir):
    return evaluate.hit_at_k(raw_links(spark, sf_dir), ["split"])


@query("q15_hit_at_k_by_channel", f"""WITH {RAW_LINKS}
    SELECT split, channel, count(*) AS links, count(*) FILTER (WHERE correct) AS correct, round(count(*) FILTER (WHERE correct) / count(*), 6) AS rate FROM links GROUP BY ALL""")
def hit_by_channel(spark, sf_dir):
    best, asked, _ = nearest_to_texts(spark, sf_dir)
    links, right = F.sum("n"), F.sum(F.when(F.col("asked") == F.col("found"), F.col("n")).otherwise(0))  # tuples of one text have the same links
    return best.join(asked, ["split", "text"]).groupBy("split", "channel").agg(links.alias("links"), right.alias("correct"), F.round(right / links, 6).alias("rate"))


def _names(spark, sf_dir):
    return table(spark, sf_dir, "part").select(F.col("p_name").alias("id"), F.col("p_name").alias("text")).distinct()


def _texts(spark, sf_dir):
    return part_mentions(spark, sf_dir).select(F.col("mention_id").alias("id"), "text")


@query("q16_link_equal", "SELECT a.page_id AS name_id, b.page_id AS text_id FROM pages a JOIN pages b ON lower(trim(regexp_extract(a.html, '<title>(.*?)</title>', 1))) = lower(trim(regexp_extract(b.html, '<h1>(.*?)</h1>', 1)))")
def link_equal(spark, sf_dir):
    pages = table(spark, sf_dir, "pages")
    part = lambda tag: pages.select(F.col("page_id").alias("id"), F.regexp_extract("html", f"<{tag}>(.*?)</{tag}>", 1).alias("text"))
    return cand.equal(part("title"), part("h1"))


@query("q17_link_contains_benchmark", "SELECT item_id AS name_id, doc_id AS text_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def link_contains(spark, sf_dir):
    return cand.contained(
        table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("id"), "text"), table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    )


SHARED = f"""{MENTIONS}, nt AS (SELECT DISTINCT p_name AS name_id, unnest({TOK('p_name')}) AS token FROM part),
    mt AS (SELECT DISTINCT mention_id AS text_id, unnest({TOK('text')}) AS token FROM mentions)"""


@query("q18_link_shared_word", f"WITH {SHARED} SELECT name_id, text_id, count(*) AS shared FROM nt JOIN mt USING (token) GROUP BY ALL")
def link_shared(spark, sf_dir):
    return cand.shared_word(_names(spark, sf_dir), _texts(spark, sf_dir))


@query("q19_candidate_union", f"""WITH {SHARED}, a AS (SELECT name_id, text_id FROM nt JOIN mt USING (token) GROUP BY ALL HAVING count(*) >= 2),
    b AS (SELECT DISTINCT p_name AS name_id, mention_id AS text_id FROM part JOIN mentions ON contains(text, p_name)),
    u AS (SELECT *, 'contains' AS s FROM b UNION ALL SELECT *, 'shared_word' FROM a)
    SELECT strategies, count(*) AS pairs FROM (SELECT name_id, text_id, string_agg(s, '+' ORDER BY s) AS strategies FROM u GROUP BY ALL) GROUP BY strategies""")
def candidate_union(spark, sf_dir):
    names, texts = _names(spark, sf_dir), _texts(spark, sf_dir)
    pools = {"shared_word": cand.shared_word(names, texts, 2), "contains": cand.contained(names, texts)}
    return cand.union_of(pools).groupBy(F.array_join("strategies", "+").alias("strategies")).agg(F.count("*").alias("pairs"))


@query("q20_no_score_all_tie", "SELECT item_id AS name_id, doc_id AS text_id, 1 AS rank FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def no_score(spark, sf_dir):
    pairs = link_contains(spark, sf_dir).withColumn("distance", F.lit(None).cast("double"))
    return rank.link_rank(pairs, "name_id", "text_id", 1).drop("distance")


@query("q21_context_window", """SELECT conv_id, turn, concat_ws(' ', lag(text) OVER w, text, lead(text) OVER w) AS context FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)""")
def context_window(spark, sf_dir):
    rows = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("doc_id"), F.col("turn").alias("sent_no"), "text")
    return src.with_context(rows).select(F.col("doc_id").alias("conv_id"), F.col("sent_no").alias("turn"), "context")


def scores(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings")
    even, odd = e.where("vec_id % 2 = 0"), e.where("vec_id % 2 = 1")
    a, b = (x.select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec")) for x in (even, odd))
    found = exact_knn(a, b, 1 << 30)
    left = even.select(F.col("vec_id").alias("query_id"), F.col("label").alias("l"))
    right = odd.select(F.col("vec_id").alias("result_id"), F.col("label").alias("m"))
    return found.join(left, "query_id").join(right, "result_id").select(
        F.col("query_id").alias("r_id"), F.col("result_id").alias("t_id"), F.round("distance", 9).alias("dist"), (F.col("l") == F.col("m")).alias("is_match")
    )


def _halves(spark, sf_dir, side: str = "relation") -> tuple[DataFrame, DataFrame]:
    """(id, vec, label) of a side's items and of the other side."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label")
    even, odd = e.where("id % 2 = 0"), e.where("id % 2 = 1")
    return (even, odd) if side == "relation" else (odd, even)


def _loss(spark, sf_dir, side: str) -> DataFrame:
    """Loss of every item of a side that has a match and a non-match."""
    found = loss.scanned_loss(*_halves(spark, sf_dir, side), 0.1).where("n > 0 and negatives > 0")
    return found.select(F.col("id").alias(loss.SIDES[side]), "loss")


SCORES = """s AS (SELECT a.vec_id AS r_id, b.vec_id AS t_id, a.label = b.label AS is_match,
    round(1 - list_inner_product(a.v, b.v) / sqrt(list_inner_product(a.v, a.v) * list_inner_product(b.v, b.v)), 9) AS dist
    FROM (SELECT *, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings WHERE vec_id % 2 = 0) a, (SELECT *, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings WHERE vec_id % 2 = 1) b)"""
PARTIAL = lambda key, m: f"""(SELECT {key}, sum(greatest(0, {m} + near - dist)) AS loss FROM (SELECT *, avg(dist) FILTER (WHERE is_match) OVER (PARTITION BY {key}) AS near FROM s)
    WHERE NOT is_match AND near IS NOT NULL GROUP BY {key})"""  # noqa: E731


@query("q22_mean_positive", f"WITH {SCORES} SELECT r_id, round(avg(dist), 6) AS mean_positive, count(*) AS n FROM s WHERE is_match GROUP BY r_id")
def mean_positive(spark, sf_dir):
    found = loss.scanned_loss(*_halves(spark, sf_dir)).where("n > 0")
    return found.select(F.col("id").alias("r_id"), F.round("mean_positive", 6).alias("mean_positive"), "n")


@query("q23_loss_relation_side", f"WITH {SCORES} SELECT r_id, round(loss, 5) AS loss FROM {PARTIAL('r_id', 0.1)}")
def loss_relation(spark, sf_dir):
    return _loss(spark, sf_dir, "relation").withColumn("loss", F.round("loss", 5))


@query("q24_loss_text_side", f"WITH {SCORES} SELECT t_id, round(loss, 5) AS loss FROM {PARTIAL('t_id', 0.1)}")
def loss_text(spark, sf_dir):
    return _loss(spark, sf_dir, "text").withColumn("loss", F.round("loss", 5))


@query("q25_loss_total", f"WITH {SCORES} SELECT round(sum(loss), 4) AS loss FROM (SELECT loss FROM {PARTIAL('r_id', 0.1)} UNION ALL SELECT loss FROM {PARTIAL('t_id', 0.1)})")
def loss_total(spark, sf_dir):
    both = [_loss(spark, sf_dir, side).select("loss") for side in loss.SIDES]
    return both[0].unionByName(both[1]).agg(F.round(F.sum("loss"), 4).alias("loss"))


@query("q26_loss_single_positive", f"""WITH {SCORES} SELECT p.r_id, round(sum(greatest(0, 0.1 + p.dist - n.dist)), 4) AS loss
    FROM s p JOIN s n ON p.r_id = n.r_id AND p.is_match AND NOT n.is_match GROUP BY p.r_id""")
def loss_single(spark, sf_dir):
    found = loss.scanned_single_loss(*_halves(spark, sf_dir), 0.1).where("n > 0 and negatives > 0")
    return found.select(F.col("id").alias("r_id"), F.round("loss", 4).alias("loss"))


@query("q27_elu_layer_forward", f"""WITH c AS (SELECT vec_id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings),
    w AS (SELECT o, i, {H("'w' || o || ',' || i")} / 4294967296.0 - 0.5 AS w FROM range(8) a(o), range(64) b(i)),
    a AS (SELECT vec_id, o, sum(x * w) AS z FROM c JOIN w USING (i) GROUP BY ALL)
    SELECT vec_id, o::INT AS o, round(CASE WHEN z > 0 THEN z ELSE exp(z) - 1 END, 6) AS y FROM a""")
def elu_forward(spark, sf_dir):
    cells = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "x"))
    w = spark.range(8 * 64).select(F.floor(F.col("id") / 64).cast("int").alias("o"), (F.col("id") % 64).cast("int").alias("i"))
    w = w.withColumn("w", h(F.concat(F.lit("w"), F.col("o").cast("string"), F.lit(","), F.col("i").cast("string"))) / 4294967296.0 - 0.5)
    z = cells.join(F.broadcast(w), "i").groupBy("vec_id", "o").agg(F.sum(F.col("x").cast("double") * F.col("w")).alias("z"))
    return z.select("vec_id", "o", F.round(elu(F.col("z")), 6).alias("y"))


@query("q28_lr_schedule", "SELECT o_orderkey AS step, round(1e-5 * pow(0.9, o_orderkey // 1000), 15) AS rate FROM orders")
def lr_schedule(spark, sf_dir):
    """Rate of the step that reads each order, one order a step in the order of keys, by the schedule of the trainer."""
    from entlink.joint.network import learning_rate

    @F.pandas_udf("double")
    def rate(steps: pd.Series) -> pd.Series:
        return learning_rate(steps, 1e-5)

    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("step"), F.round(rate("o_orderkey"), 15).alias("rate"))


def seen_counts(spark, sf_dir):
    m = part_mentions(spark, sf_dir)
    return m.select("tuple_id", "mention_id", (h(F.concat(F.lit("s"), F.col("mention_id"))) % 50).alias("seen"))


SEEN = f"{MENTIONS}, c AS (SELECT tuple_id, mention_id, {H(chr(39) + 's' + chr(39) + ' || mention_id')} % 50 AS seen FROM mentions)"


@query("q29_sampler_weights", f"""WITH {SEEN}, w AS (SELECT *, avg(seen) OVER () AS a FROM c), x AS (SELECT *, pow(1.0 + seen, -1.0) AS weight FROM w WHERE seen <= 4.0 * a + 1),
    d AS (SELECT *, -ln(({H("'b1' || tuple_id || '|' || mention_id")} + 0.5) / 4294967296.0) / weight AS draw FROM x)
    SELECT tuple_id, mention_id, seen, round(weight, 6) AS weight, round(draw, 6) AS draw FROM d ORDER BY d.draw, tuple_id, mention_id LIMIT 64""")
def sampler(spark, sf_dir):
    drawn = loss.draw_pairs(loss.sampler_weights(seen_counts(spark, sf_dir)), 64, "b1")
    return drawn.select("tuple_id", "mention_id", "seen", F.round("weight", 6).alias("weight"), F.round("draw", 6).alias("draw"))


@query("q30_negatives_antijoin", f"""WITH {MENTIONS}, o AS (SELECT mention_id AS text_id, row_number() OVER (ORDER BY {H('mention_id')}, mention_id) AS place FROM mentions),
    p AS (SELECT DISTINCT p_name AS name_id, i, {H("p_name || '#' || i")} % (SELECT count(*) FROM mentions) + 1 AS place FROM part, range(1, 3) r(i))
    SELECT DISTINCT name_id, text_id FROM p JOIN o USING (place) WHERE NOT EXISTS (SELECT 1 FROM mentions m WHERE m.instance_id = name_id AND m.mention_id = text_id)""")
def negatives(spark, sf_dir):
    gold = part_mentions(spark, sf_dir).select(F.col("instance_id").alias("name_id"), F.col("mention_id").alias("text_id"))
    return cand.non_matches(_names(spark, sf_dir), _texts(spark, sf_dir), gold)


def _best(spark, sf_dir, side: str) -> DataFrame:
    """The ten nearest of the other side for every item of a side, by distances of nine digits."""
    items, others = _halves(spark, sf_dir, side)
    key, other = ("tuple_id", "mention_id") if side == "relation" else ("mention_id", "tuple_id")
    found = exact_knn(items, others, 10, digits=9)
    return found.select(F.col("query_id").alias(key), F.col("result_id").alias(other), "distance", "rank")


@query("q31_mutual_best", f"""WITH {SCORES}, a AS (SELECT *, row_number() OVER (PARTITION BY r_id ORDER BY dist, t_id) AS i, row_number() OVER (PARTITION BY t_id ORDER BY dist, r_id) AS j FROM s)
    SELECT r_id AS tuple_id, t_id AS mention_id FROM a WHERE i = 1 AND j = 1""")
def mutual_best(spark, sf_dir):
    return rank.mutual(_best(spark, sf_dir, "relation"), _best(spark, sf_dir, "text"))


@query("q32_instance_rollup", f"""WITH {SCORES}, top AS (SELECT *, row_number() OVER (PARTITION BY t_id ORDER BY dist, r_id) AS rank FROM s QUALIFY rank <= 10),
    j AS (SELECT t_id, label AS instance_id, r_id, dist FROM top JOIN embeddings ON r_id = vec_id)
    SELECT t_id AS mention_id, instance_id, r_id AS tuple_id, round(dist, 6) AS distance FROM j QUALIFY row_number() OVER (PARTITION BY t_id, instance_id ORDER BY dist, r_id) = 1""")
def instance_rollup(spark, sf_dir):
    tuples = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("tuple_id"), F.col("label").alias("instance_id"))
    out = rank.rollup_instances(_best(spark, sf_dir, "text"), tuples, "mention_id")
    return out.select("mention_id", "instance_id", "tuple_id", F.round("distance", 6).alias("distance"))


@query("q33_rank_metrics", f"""WITH {SCORES}, top AS (SELECT *, row_number() OVER (PARTITION BY r_id ORDER BY dist, t_id) AS rank FROM s QUALIFY rank <= 10),
    r AS (SELECT *, sum(is_match::INT) OVER (PARTITION BY r_id ORDER BY rank) AS so_far FROM top), n AS (SELECT r_id, count(*) FILTER (WHERE is_match) AS n FROM s GROUP BY r_id)
    SELECT r_id AS query_id, round(sum(is_match::INT) / 10, 6) AS precision_at_k, round(sum(is_match::INT) / any_value(n), 6) AS recall_at_k,
           round(coalesce(1 / min(rank) FILTER (WHERE is_match), 0), 6) AS reciprocal_rank, round(sum(CASE WHEN is_match THEN so_far / rank ELSE 0 END) / least(any_value(n), 10), 6) AS average_precision
    FROM r JOIN n USING (r_id) GROUP BY r_id""")
def rank_metrics(spark, sf_dir):
    s = scores(spark, sf_dir)
    top = rank.top_n(s.withColumn("distance", F.col("dist")), "r_id", "t_id", 10).select(F.col("r_id").alias("query_id"), "rank", F.col("is_match").alias("correct"))
    n = s.groupBy(F.col("r_id").alias("query_id")).agg(F.sum(F.col("is_match").cast("bigint")).alias("n"))
    return evaluate.ranking_metrics(top, n, 10)


def masked_parts(spark, sf_dir, density: int) -> DataFrame:
    part = table(spark, sf_dir, "part")
    keep = lambda c: h(F.concat(F.col("p_partkey").cast("string"), F.lit(c))) % 100 < density
    return part.select("p_partkey", "p_name", *[F.when(keep(c), F.col(c)).alias(c) for c in ("p_brand", "p_type", "p_size", "p_retailprice")])


_mask = lambda c, d: f"({H(f'p_partkey || {chr(39)}{c}{chr(39)}')} % 100 < {d} AND {c} IS NOT NULL)::INT"


@query("q34_density_sweep", " UNION ALL ".join(f"SELECT {d} AS target, round(avg(({' + '.join(_mask(c, d) for c in ('p_brand', 'p_type', 'p_size', 'p_retailprice'))}) / 4.0), 6)::DOUBLE AS density FROM part" for d in (1, 10, 20, 100)))
def density_sweep(spark, sf_dir):
    out = None
    for d in (1, 10, 20, 100):
        filled = sum((F.col(c).isNotNull().cast("int") for c in ("p_brand", "p_type", "p_size", "p_retailprice")), F.lit(0)) / 4
        row = masked_parts(spark, sf_dir, d).agg(F.round(F.avg(filled), 6).alias("density")).select(F.lit(d).alias("target"), "density")
        out = row if out is None else out.unionByName(row)
    return out


@query("q35_accuracy_vs_density", f"""WITH {RAW_LINKS}, q AS (SELECT query_id, max(correct::INT) FILTER (WHERE rank = 1) AS hit FROM links GROUP BY split, query_id),
    n AS (SELECT tuple_id AS query_id, len({TOK('text')}) AS words FROM tuples)
    SELECT words, count(*) AS queries, round(avg(hit), 6) AS hit_at_1 FROM q JOIN n USING (query_id) GROUP BY words""")
def accuracy_vs_density(spark, sf_dir):
    tuples, _ = src.entity_type(spark, sf_dir, "product-name")
    hits = raw_links(spark, sf_dir).groupBy("split", "query_id").agg(F.max(F.when(F.col("rank") == 1, F.col("correct").cast("int"))).alias("hit"))
    n = tuples.select(F.col("tuple_id").alias("query_id"), F.size(tokens(F.col("text"))).cast("bigint").alias("words"))
    return hits.join(n, "query_id").groupBy("words").agg(F.count("*").alias("queries"), F.round(F.avg("hit"), 6).alias("hit_at_1"))


@query("q36_zipf_skew", """WITH c AS (SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1)
    SELECT l_partkey, n, row_number() OVER w AS rank, round(sum(n) OVER (w ROWS UNBOUNDED PRECEDING) / sum(n) OVER (), 6) AS share FROM c WINDOW w AS (ORDER BY n DESC, l_partkey)""")
def zipf_skew(spark, sf_dir):
    return evaluate.skew(table(spark, sf_dir, "lineitem"), "l_partkey")


@query("q37_drift_tv", f"""WITH o AS (SELECT p_brand, count(*) AS n FROM part WHERE {H('p_partkey::VARCHAR')} % 10 >= 3 GROUP BY 1), w AS (SELECT p_brand, count(*) AS n FROM part GROUP BY 1)
    SELECT round(sum(abs(coalesce(o.n / (SELECT sum(n) FROM o), 0) - coalesce(w.n / (SELECT sum(n) FROM w), 0))) / 2, 6) AS total_variation FROM o FULL JOIN w ON o.p_brand = w.p_brand""")
def drift_tv(spark, sf_dir):
    part = table(spark, sf_dir, "part")
    return evaluate.drift(part.where(h(F.col("p_partkey").cast("string")) % 10 >= 3), part, "p_brand")


@query("q38_triples_unpivot", """SELECT p_partkey::VARCHAR AS subject, unnest(['p_name', 'p_brand', 'p_type', 'p_size']) AS predicate, unnest([p_name, p_brand, p_type, p_size::VARCHAR]) AS object FROM part""")
def triples_unpivot(spark, sf_dir):
    from entlink.sources.triples import to_triples

    return to_triples(table(spark, sf_dir, "part"), "p_partkey", ["p_name", "p_brand", "p_type", "p_size"])


@query("q39_triples_pivot", "SELECT p_partkey::VARCHAR AS subject, p_name, p_brand, p_type, p_size::VARCHAR AS p_size FROM part")
def triples_pivot(spark, sf_dir):
    from entlink.sources.triples import pivot_triples

    return pivot_triples(triples_unpivot(spark, sf_dir), ["p_name", "p_brand", "p_type", "p_size"])


LSH = """w AS (SELECT t::INT AS table_no, b::INT AS bit, i, ('0x' || substr(md5(t || '|' || b || '|' || i), 1, 8))::BIGINT / 2147483648.0 - 1.0 AS w FROM range(4) a(t), range(6) c(b), range(64) d(i)),
    x AS (SELECT vec_id AS id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings),
    dots AS (SELECT id, table_no, bit, sum(x * w) AS d FROM x JOIN w USING (i) GROUP BY ALL),
    found AS (SELECT id, table_no, sum(CASE WHEN d > 0 THEN 1 << bit ELSE 0 END)::INT AS bucket FROM dots GROUP BY ALL)"""


@query("q40_sign_lsh_buckets", f"WITH {LSH} SELECT * FROM found")
def lsh_buckets(spark, sf_dir):
    return signs.buckets(vectors(spark, sf_dir), 4, 6, 64)


@query("q41_lsh_candidates", f"WITH {LSH} SELECT DISTINCT a.id AS a_id, b.id AS b_id FROM found a JOIN found b ON a.table_no = b.table_no AND a.bucket = b.bucket AND a.id < b.id")
def lsh_candidates(spark, sf_dir):
    return signs.candidates(lsh_buckets(spark, sf_dir))


@query("q42_dedup_encode_once", f"SELECT doc_id, len({TOK('text')})::INT AS n_tokens FROM documents")
def encode_once(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").withColumn("key", F.md5("text"))
    once = docs.groupBy("key").agg(F.min("text").alias("text")).select("key", F.size(tokens(F.col("text"))).alias("n_tokens"))
    return docs.join(once, "key").select("doc_id", "n_tokens")


@query("q56_detect_mentions", f"""WITH {MENTIONS}, s AS (SELECT mention_id, list_filter(regexp_split_to_array(lower(text), '[^\\p{{L}}\\p{{N}}]+'), lambda t: t <> '') AS t FROM mentions),
    g AS (SELECT mention_id, a AS token_no, array_to_string(list_slice(t, a + 1, a + 2), ' ') AS said FROM s, range(0, 40) r(a) WHERE a + 2 <= len(t))
    SELECT name_id, mention_id AS doc_id, token_no::INT AS token_no FROM g JOIN (SELECT DISTINCT p_name AS name_id FROM part) ON said = name_id""")
def detect_mentions(spark, sf_dir):
    sents = part_mentions(spark, sf_dir).select(F.col("mention_id").alias("doc_id"), F.lit(0).alias("sent_no"), "text")
    return cand.detect(sents, _names(spark, sf_dir), 2).select("name_id", "doc_id", "token_no")


@query("q57_separation", f"""WITH {SCORES}, r AS (SELECT *, avg(dist) FILTER (WHERE is_match) OVER (PARTITION BY r_id) + 0.1 AS ring FROM s)
    SELECT round(avg(dist) FILTER (WHERE is_match), 6) AS mean_positive, round(avg(dist) FILTER (WHERE NOT is_match), 6) AS mean_negative,
           round(avg((dist > ring)::INT) FILTER (WHERE NOT is_match), 6) AS outside FROM r""")
def separation(spark, sf_dir):
    return evaluate.separation(scores(spark, sf_dir), 0.1)


@query("q58_pair_distance", """SELECT a.vec_id AS id, round(1 - list_inner_product(a.v, b.v) / sqrt(list_inner_product(a.v, a.v) * list_inner_product(b.v, b.v)), 6) AS distance
    FROM (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings) a JOIN (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings) b ON b.vec_id = a.vec_id + 1""")
def pair_distance(spark, sf_dir):
    e = vectors(spark, sf_dir)
    after = e.select((F.col("id") - 1).alias("id"), F.col("vec").alias("w"))
    return e.join(after, "id").select("id", F.round(cosine_distance(F.col("vec"), F.col("w")), 6).alias("distance"))


@query("q59_reverse_fk", "SELECT p_partkey, round(coalesce(sum(l_quantity), 0), 2) AS l_quantity, round(coalesce(sum(l_extendedprice), 0), 2) AS l_extendedprice FROM part LEFT JOIN lineitem ON l_partkey = p_partkey GROUP BY 1")
def reverse_fk(spark, sf_dir):
    out = vectorize.reverse_fk(table(spark, sf_dir, "part"), "p_partkey", table(spark, sf_dir, "lineitem"), "l_partkey", ["l_quantity", "l_extendedprice"])
    return out.select("p_partkey", F.round("l_quantity", 2).alias("l_quantity"), F.round("l_extendedprice", 2).alias("l_extendedprice"))

