"""Experiments: profiles, sweeps over density and mentions, skewed training, several gold mappings, reports."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entlink.functions.text import h
from entlink.joint.train import Config, mention_vector
from entlink.operators.candidates import blocks, shared_word
from entlink.operators.evaluate import hit_at_k, profile
from entlink.operators.ordering import ntile, ranked
from entlink.operators.rank import top_n
from entlink.plans.accuracy import accuracy_table, entity_frames, links_of, relation_vectors, trained
from entlink.registry import query
from entlink.sources.mentions import TYPE_NAMES, entity_type, relations, spoken_parts, verbalized, with_split
from entlink.spec import BY_NAME
from entlink.storage import materialize, table
from entlink.workloads.core import H, MENTIONS, RAW_LINKS, TOK, masked_parts, raw_links

QUICK = Config(steps=150)
DENSITIES = (1, 10, 20, 100)


def _columns(name: str) -> tuple[str, str, str, list[str]]:
    """Table, key and attributes with foreign keys of a type's relation, and its instance."""
    spec = BY_NAME[name]
    return spec.table, spec.key, spec.instance, [*spec.attributes, *[f.column for f in spec.foreign_keys]]


_RELATIONS = {"pages": "(SELECT page_id, url, regexp_extract(html, '<title>(.*?)</title>', 1) AS title FROM pages)", "conversations": "(SELECT * FROM conversations WHERE turn = 0)"}


def _profile_sql(name: str) -> str:
    table_, _, instance, cols = _columns(name)
    filled = " + ".join(f"({c} IS NOT NULL)::INT" for c in cols)
    return f"""SELECT '{name}' AS entity_type, count(DISTINCT {instance}) AS instances, count(*) AS tuples, {len(cols)} AS columns,
        round(avg(({filled}) / {len(cols)}.0), 6)::DOUBLE AS density FROM {_RELATIONS.get(table_, table_)}"""


@query("q119_profile_columns", " UNION ALL ".join(_profile_sql(n) for n in TYPE_NAMES))
def profile_columns(spark, d):
    """Instances, tuples, columns and mean density of the relation of every type."""
    found, rows = relations(spark, d), []
    for name in TYPE_NAMES:
        table_, _, instance, cols = _columns(name)
        filled = sum((F.col(c).isNotNull().cast("int") for c in cols), F.lit(0)) / len(cols)
        rows.append(found[table_].agg(F.countDistinct(instance).alias("instances"), F.count("*").alias("tuples"), F.lit(len(cols)).alias("columns"), F.round(F.avg(filled), 6).alias("density")).select(F.lit(name).alias("entity_type"), "*"))
    return reduce(DataFrame.unionByName, rows)


@query("q102_profile_ten_types")
def profile_ten(spark, d):
    """Instances, tuples, mentions, mentions per instance, columns and mean density of every type."""
    found, rows = relations(spark, d), []
    for name in TYPE_NAMES:
        table_, key, _, cols = _columns(name)
        tuples, mentions = entity_type(spark, d, name)
        attributes = found[table_].select(F.col(key).cast("string").alias("tuple_id"), *[F.col(c).alias(f"a_{i}") for i, c in enumerate(cols)])
        rows.append(profile(tuples.join(attributes, "tuple_id"), [f"a_{i}" for i in range(len(cols))], "instance_id", mentions).select(F.lit(name).alias("entity_type"), "*"))
    return reduce(DataFrame.unionByName, rows)


def _density_table(spark, d):
    """Hit rates of single products as more of their attributes are null: the relation vectors of masked tables."""
    part = table(spark, d, "part")
    mentions = spoken_parts(part).withColumn("instance_id", F.col("tuple_id")).withColumn("context", F.lit(""))
    mentions = materialize(with_split(mentions.withColumn("vec", mention_vector(QUICK)).select(F.lit("product").alias("entity_type"), "*")), "density-mentions")
    key, out = F.col("p_partkey").cast("string"), []
    for density in DENSITIES:
        masked = materialize(masked_parts(spark, d, density), "density-parts")
        vectors = relation_vectors(spark, d, "product", QUICK, tables={"part": masked})
        tuples = masked.select(F.lit("product").alias("entity_type"), key.alias("tuple_id"), key.alias("instance_id"), F.col("p_name").alias("text"))
        tuples = materialize(tuples.join(vectors, "tuple_id"), "density-tuples")
        got = hit_at_k(links_of(tuples, mentions, trained(tuples, mentions, QUICK), QUICK), ["split"])
        out.append(got.withColumn("density", F.lit(density)))
    return reduce(DataFrame.unionByName, out)


@query("q103_density_accuracy")
def density_accuracy(spark, d):
    return _density_table(spark, d)


@query("q116_density_correlation")
def density_correlation(spark, d):
    """Correlation of the share of attributes that are known with hit rates at 1, for every split."""
    rows = _density_table(spark, d).where("k = 1")
    return rows.groupBy("split").agg(F.count("*").alias("densities"), F.round(F.corr("density", "rate"), 6).alias("correlation"), F.round(F.corr(F.log("density"), "rate"), 6).alias("log_correlation"))


@query("q104_fanout_accuracy")
def fanout_accuracy(spark, d):
    """Hit rates as tuples have more mentions to learn from."""
    out = []
    tuples, _ = entity_frames(spark, d, ("product-name",), QUICK)
    for fanout in (1, 3, 6):
        said = spoken_parts(table(spark, d, "part"), fanout).withColumn("context", F.lit("")).withColumn("vec", mention_vector(QUICK))
        mentions = materialize(with_split(said.select(F.lit("product-name").alias("entity_type"), "*")), "fanout-mentions")
        got = hit_at_k(links_of(tuples, mentions, trained(tuples, mentions, QUICK), QUICK), ["split"])
        out.append(got.withColumn("fanout", F.lit(fanout)))
    return reduce(DataFrame.unionByName, out)


@query("q113_word_exact_hits", f"""WITH {MENTIONS}, q AS (SELECT DISTINCT s.split, tuple_id, instance_id, t.text FROM tuples t JOIN (SELECT DISTINCT instance_id, split FROM split) s USING (instance_id)),
    a AS (SELECT DISTINCT split, tuple_id, instance_id, unnest({TOK('text')}) AS token FROM q), b AS (SELECT DISTINCT split, mention_id, instance_id AS said, unnest({TOK('text')}) AS token FROM split),
    n AS (SELECT a.split, tuple_id, mention_id, any_value(instance_id = said) AS correct, count(*) AS shared FROM a JOIN b ON a.split = b.split AND a.token = b.token GROUP BY ALL),
    r AS (SELECT *, row_number() OVER (PARTITION BY split, tuple_id ORDER BY shared DESC, mention_id) AS rank FROM n),
    best AS (SELECT q.split, q.tuple_id, min(rank) FILTER (WHERE correct) AS best FROM q LEFT JOIN r USING (split, tuple_id) GROUP BY ALL)
    SELECT split, k::INT AS k, count(*) FILTER (WHERE best <= k) AS hits, count(*) AS queries, round(count(*) FILTER (WHERE best <= k) / count(*), 6) AS rate
    FROM best, (VALUES (1), (5), (10)) t(k) GROUP BY split, k""")
def word_exact_hits(spark, d):
    """Hit rates of the word join without learning: mentions by the number of words that they share with the tuple."""
    tuples, mentions = entity_type(spark, d, "product-name")
    marked = with_split(mentions)
    out = []
    for split in ("train", "test", "unseen"):
        pool = marked.where(F.col("split") == split)
        asked = tuples.join(pool.select("instance_id").distinct(), "instance_id", "left_semi")
        pairs = shared_word(asked.select(F.col("tuple_id").alias("id"), "text"), pool.select(F.col("mention_id").alias("id"), "text"))
        top = top_n(pairs.withColumn("distance", -F.col("shared")), "name_id", "text_id", 10)
        known = pool.select(F.col("mention_id").alias("text_id"), F.col("instance_id").alias("said"))
        links = asked.select(F.col("tuple_id").alias("name_id"), "instance_id").join(top.join(known, "text_id"), "name_id", "left")
        out.append(hit_at_k(links.select(F.lit(split).alias("split"), F.col("name_id").alias("query_id"), "rank", (F.col("said") == F.col("instance_id")).alias("correct")), ["split"]))
    return reduce(DataFrame.unionByName, out)


@query("q117_rarest_token_blocks", f"""WITH {MENTIONS}, nt AS (SELECT DISTINCT p_name AS name_id, unnest({TOK('p_name')}) AS token FROM part), mt AS (SELECT DISTINCT mention_id AS text_id, unnest({TOK('text')}) AS token FROM mentions),
    df AS (SELECT token, count(*) AS df FROM mt GROUP BY token), k AS (SELECT name_id, token FROM nt JOIN df USING (token) QUALIFY row_number() OVER (PARTITION BY name_id ORDER BY df, token) = 1)
    SELECT name_id, count(*) AS texts FROM k JOIN mt USING (token) GROUP BY name_id""")
def rarest_token_blocks(spark, d):
    """How many texts each name meets in the block of its rarest word."""
    names = table(spark, d, "part").select(F.col("p_name").alias("id"), F.col("p_name").alias("text")).distinct()
    texts = verbalized(table(spark, d, "part")).select(F.col("mention_id").alias("id"), "text")
    return blocks(names, texts).groupBy("name_id").agg(F.count("*").alias("texts"))


@query("q105_knn_report", f"""WITH {RAW_LINKS}
    SELECT l.split, l.query_id, l.result_id, l.rank::INT AS rank, t.text AS tuple_text, m.text AS mention_text FROM links l JOIN tuples t ON l.query_id = t.tuple_id JOIN mentions m ON l.result_id = m.mention_id WHERE l.rank <= 3""")
def knn_report(spark, d):
    """The nearest mentions of every tuple, joined back to both tables after ranking."""
    tuples, mentions = entity_type(spark, d, "product-name")
    links = raw_links(spark, d, 10).where("rank <= 3").select("split", "query_id", "result_id", "rank")
    a = tuples.select(F.col("tuple_id").alias("query_id"), F.col("text").alias("tuple_text"))
    b = mentions.select(F.col("mention_id").alias("result_id"), F.col("text").alias("mention_text"))
    return links.join(a, "query_id").join(b, "result_id").select("split", "query_id", "result_id", "rank", "tuple_text", "mention_text")


ZIPF = f"""{MENTIONS}, n AS (SELECT instance_id, row_number() OVER (ORDER BY {H('instance_id')}, instance_id) AS r FROM (SELECT DISTINCT instance_id FROM mentions)),
    z AS (SELECT m.*, row_number() OVER (PARTITION BY instance_id ORDER BY {H('mention_id')}, mention_id) AS i, r FROM mentions m JOIN n USING (instance_id))"""


def zipf_mentions(mentions: DataFrame, most: int = 96) -> DataFrame:
    """Mentions thinned so that the instance of popularity rank r keeps about ``most`` / r of them."""
    hashed = mentions.select("instance_id").distinct().withColumn("hash", h(F.col("instance_id")))
    names = ranked(hashed, ["hash", "instance_id"], "r", "zipf")[0].select("instance_id", (F.col("r") + 1).cast("int").alias("r"))
    w = Window.partitionBy("instance_id").orderBy(h(F.col("mention_id")), "mention_id")
    rows = mentions.join(names, "instance_id").withColumn("i", F.row_number().over(w))
    return rows.where(F.col("i") <= F.greatest(F.lit(1), F.floor(F.lit(most) / F.col("r")))).drop("i")


@query("q106_zipf_mentions", f"WITH {ZIPF} SELECT instance_id, r::INT AS r, count(*) AS n FROM z WHERE i <= greatest(1, floor(96 / r)) GROUP BY ALL")
def zipf(spark, d):
    return zipf_mentions(verbalized(table(spark, d, "part"))).groupBy("instance_id", "r").agg(F.count("*").alias("n"))


@query("q107_skewed_training")
def skewed_training(spark, d):
    """Training on Zipf-distributed mentions with either sampler: hit rates of head, torso and tail instances."""
    tuples, mentions = entity_frames(spark, d, ("product-name",), QUICK)
    skewed = materialize(zipf_mentions(mentions), "zipf")
    third = ntile(skewed.select("instance_id", "r").distinct(), ["r"], 3, "third").drop("r")
    out = []
    for sampler in ("skew", "uniform"):
        c = replace(QUICK, sampler=sampler)
        links = links_of(tuples, mentions, trained(tuples, skewed, c), c)
        inst = tuples.select(F.col("tuple_id").alias("query_id"), "instance_id")
        got = hit_at_k(links.join(inst, "query_id").join(third, "instance_id"), ["third", "split"])
        out.append(got.withColumn("sampler", F.lit(sampler)))
    return reduce(DataFrame.unionByName, out)


@query("q108_many_to_many")
def many_to_many(spark, d):
    """Types with natural gold: passages in several documents (1-N) and copies of documents (M-N)."""
    return accuracy_table(spark, d, ("passage", "copied-document", "page", "dialogue"), QUICK)


@query("q109_accuracy_against_profile")
def accuracy_against_profile(spark, d):
    """Correlation over types of unseen hit rates with mentions per instance."""
    acc = accuracy_table(spark, d, config=replace(QUICK, steps=100)).where("split = 'unseen' and k = 1").select("entity_type", "rate")
    both = acc.join(profile_ten(spark, d).select("entity_type", "per_instance"), "entity_type")
    return both.agg(F.count("*").alias("types"), F.round(F.corr("rate", "per_instance"), 6).alias("correlation"), F.round(F.corr("rate", F.log("per_instance")), 6).alias("log_correlation"))


@query("q110_shuffled_gold_control")
def shuffled_gold(spark, d):
    """Training on gold links whose instances are shuffled: unseen hit rates must fall to what chance gives."""
    c = replace(QUICK, dim=128)
    tuples, mentions = entity_frames(spark, d, ("supplier",), c)
    names = mentions.select("instance_id").distinct().withColumn("hash", h(F.col("instance_id")))
    a = ranked(names, ["instance_id"], "i", "names")[0].select("instance_id", "i")
    b = ranked(names, ["hash", "instance_id"], "i", "others")[0].select(F.col("instance_id").alias("other"), "i")
    wrong = a.join(b, "i").select("instance_id", "other")
    mixed = materialize(mentions.join(wrong, "instance_id").drop("instance_id").withColumnRenamed("other", "instance_id"), "shuffled")
    rows = []
    for label, gold in (("true", mentions), ("shuffled", mixed)):
        links = links_of(tuples, gold, trained(tuples, gold, c), c)
        rows.append(hit_at_k(links, ["split"]).withColumn("gold", F.lit(label)))
    return rows[0].unionByName(rows[1])
