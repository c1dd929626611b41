"""Ten entity types on the given tables: tuples, mentions and gold links.

The star tables have no natural mentions, so their tuples are put into words:
templates vary order and omit attributes, and channels bring in the errors a
linker meets (homonyms, hyponyms, synonyms, misspellings).  All choices hash
the key, so every run and every engine makes the same sentences.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from entlink.functions.text import h
from entlink.storage import held, materialize, spread, table

FANOUT = 3
BROADER = {"anvil": "tool", "bolt": "fastener", "gear": "machine part", "gizmo": "device", "plate": "sheet", "ring": "band", "rod": "bar", "widget": "gadget"}
ALIKE = {"small": "compact", "large": "huge", "red": "crimson", "blue": "azure", "hot": "warm", "cold": "chilly", "old": "aged", "new": "fresh"}
CHANNELS = ("clean", "homonym", "hyponym", "synonym", "misspelling")


def channel_of(key: Column, i: Column) -> Column:
    n = h(F.concat(F.lit("c"), key, F.lit("#"), i)) % 10
    return F.when(n < 6, "clean").when(n == 6, "homonym").when(n == 7, "hyponym").when(n == 8, "synonym").otherwise("misspelling")


def _swap(word: Column, pairs: dict[str, str]) -> Column:
    out = word
    for a, b in pairs.items():
        out = F.when(word == a, F.lit(b)).otherwise(out)
    return out


def spoken_name(name: Column, channel: Column, seed: Column) -> Column:
    """A two-word name as the channel says it."""
    first, rest = F.substring_index(name, " ", 1), F.substring_index(name, " ", -1)
    drop = (h(F.concat(F.lit("m"), seed)) % F.length(name)).cast("int")
    return (
        F.when(channel == "hyponym", F.concat_ws(" ", first, _swap(rest, BROADER)))
        .when(channel == "synonym", F.concat_ws(" ", _swap(first, ALIKE), rest))
        .when(channel == "misspelling", F.concat(F.substring(name, F.lit(1), drop), F.substring(name, drop + 2, F.length(name))))
        .otherwise(name)
    )


def verbalized(parts: DataFrame, fanout: int = FANOUT) -> DataFrame:
    """``fanout`` sentences for every part: mention_id, tuple_id, instance_id, channel, text."""
    return spoken_parts(parts, fanout).drop("span")


def spoken_parts(parts: DataFrame, fanout: int = FANOUT) -> DataFrame:
    """As ``verbalized``, with ``span``, the words of the text that name the part."""
    rows = parts.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(fanout - 1))))
    key, i = F.col("p_partkey").cast("string"), F.col("i").cast("string")
    seed = F.concat(key, F.lit("#"), i)
    rows = rows.withColumn("seed", seed).withColumn("channel", channel_of(key, i))
    rows = rows.withColumn("said", spoken_name(F.col("p_name"), F.col("channel"), F.col("seed")))
    size, form = F.col("p_size").cast("string"), h(F.concat(F.lit("t"), F.col("seed"))) % 4
    said, brand, kind = F.col("said"), F.col("p_brand"), F.lower("p_type")
    text = (
        F.when(F.col("channel") == "homonym", F.concat(F.lit("Someone asked about the "), said, F.lit(".")))
        .when(form == 0, F.concat(F.lit("The "), said, F.lit(" from "), brand, F.lit(" comes in size "), size, F.lit(" and belongs to the "), kind, F.lit(" line.")))
        .when(form == 1, F.concat(F.lit("In size "), size, F.lit(", "), brand, F.lit(" sells a "), said, F.lit(".")))
        .when(form == 2, F.concat(F.lit("Among "), kind, F.lit(" goods the "), said, F.lit(" is the pride of "), brand, F.lit(".")))
        .otherwise(F.concat(F.lit("Our shop keeps a "), said, F.lit(". It has size "), size, F.lit(" and was made by "), brand, F.lit(".")))
    )
    return rows.select(F.col("seed").alias("mention_id"), key.alias("tuple_id"), F.col("p_name").alias("instance_id"), "channel", text.alias("text"), said.alias("span"))


def _spoken(rows: DataFrame, key: str, words: list[Column], instance: Column | None = None, fanout: int = FANOUT) -> DataFrame:
    """Plain sentences for types whose names are codes: each leaves another attribute out."""
    rows = rows.withColumn("_i", F.explode(F.sequence(F.lit(0), F.lit(fanout - 1))))
    k = F.col(key).cast("string")
    said = [F.when(F.col("_i") % len(words) != j, w) if len(words) > 1 and j else w for j, w in enumerate(words)]
    form = h(F.concat(F.lit("t"), k, F.lit("#"), F.col("_i").cast("string"))) % 2
    text = F.when(form == 0, F.concat(F.lit("We heard of "), F.concat_ws(" with ", *said), F.lit("."))).otherwise(
        F.concat(F.concat_ws(", also ", *reversed(said)), F.lit(" was in the news."))
    )
    return rows.select(
        F.concat(k, F.lit("#"), F.col("_i").cast("string")).alias("mention_id"), k.alias("tuple_id"), (instance if instance is not None else k).alias("instance_id"),
        F.lit("clean").alias("channel"), text.alias("text"), words[0].alias("span"),
    )


def _tuples(rows: DataFrame, key: str, text: list[Column], instance: Column | None = None) -> DataFrame:
    k = F.col(key).cast("string")
    return rows.select(k.alias("tuple_id"), (instance if instance is not None else k).alias("instance_id"), F.concat_ws(" ", *text).alias("text"))


def paragraphs(pages: DataFrame) -> DataFrame:
    """Paragraph texts of web pages: page_id, no, text."""
    parts = pages.select("page_id", F.posexplode(F.split(F.coalesce("html", F.lit("")), "<p>")).alias("no", "raw")).where("no > 0")
    clean = F.trim(F.regexp_replace(F.regexp_replace("raw", "<[^>]*>", " "), r"\s+", " "))
    return parts.select("page_id", "no", clean.alias("text")).where("text != ''")


def relations(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """The relations that the entity types vectorise, by the table names of their specifications."""
    found = {n: table(spark, sf_dir, n) for n in ("region", "nation", "customer", "supplier", "part", "orders", "benchmark", "documents")}
    found |= {n: spread(found[n]) for n in ("customer", "part", "orders")}
    pages = table(spark, sf_dir, "pages")
    found["pages"] = pages.select("page_id", "url", F.regexp_extract("html", "<title>(.*?)</title>", 1).alias("title"))
    found["conversations"] = table(spark, sf_dir, "conversations").where("turn = 0")
    return found


def _sentence_mentions(pairs: DataFrame, docs: DataFrame, which) -> DataFrame:
    """Mentions from single sentences of documents, with their neighbours: pairs has tuple_id, instance_id, doc_id and what ``which`` reads."""
    pairs = materialize(pairs, "pairs")
    some = docs.join(held(pairs.select("doc_id").distinct(), "pair-docs"), "doc_id", "left_semi")
    sents = with_context(sentences(some)).withColumn("text", F.trim("text"))
    rows = sents.join(pairs, "doc_id").where(which)
    key = F.concat_ws("#", "tuple_id", F.col("doc_id").cast("string"), F.col("sent_no").cast("string"))
    return rows.select(key.alias("mention_id"), "tuple_id", "instance_id", F.lit("natural").alias("channel"), "text", F.lit("").alias("span"), "context")


def entity_type(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """Tuples (tuple_id, instance_id, text) and mentions (mention_id, tuple_id, instance_id, channel, text, span, context) of a type.

    ``span`` holds the words that name the entity, ``text`` the sentence and ``context`` what stands around it.
    """
    tuples, mentions = _entity_type(spark, sf_dir, name)
    if "context" not in mentions.columns:  # what follows the first sentence
        mentions = mentions.withColumn("context", F.regexp_extract("text", r"^[^.]*\.\s+(.+)$", 1))
    if "span" not in mentions.columns:
        mentions = mentions.withColumn("span", F.lit(""))
    return tuples, mentions


def _entity_type(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    t = lambda n: table(spark, sf_dir, n)
    num = lambda c: F.round(F.col(c)).cast("bigint").cast("string")
    if name in ("product-name", "product"):
        part = spread(t("part"))
        inst = F.col("p_name") if name == "product-name" else None
        mentions = spoken_parts(part)
        if inst is None:
            mentions = mentions.withColumn("instance_id", F.col("tuple_id"))
        return _tuples(part, "p_partkey", [F.col("p_name"), F.col("p_brand"), F.lower("p_type"), F.concat(F.lit("size "), F.col("p_size").cast("string"))], inst), mentions
    nation = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    if name == "nation":
        words = [F.col("n_name"), F.col("r_name")]
        return _tuples(nation, "n_nationkey", words), _spoken(nation, "n_nationkey", words, fanout=12)
    if name == "customer":
        rows = spread(t("customer")).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
        words = [F.col("c_name"), F.col("n_name"), F.col("c_mktsegment"), F.concat(F.lit("balance "), num("c_acctbal"))]
        return _tuples(rows, "c_custkey", words), _spoken(rows, "c_custkey", words)
    if name == "supplier":
        rows = t("supplier").join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey"))
        words = [F.col("s_name"), F.col("n_name"), F.concat(F.lit("balance "), num("s_acctbal"))]
        return _tuples(rows, "s_suppkey", words), _spoken(rows, "s_suppkey", words)
    if name == "order":
        rows = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
        words = [F.concat(F.lit("order "), F.col("o_orderkey").cast("string")), F.col("c_name"), F.col("o_orderpriority"), F.concat(F.lit("total "), num("o_totalprice"))]
        return _tuples(rows, "o_orderkey", words), _spoken(rows, "o_orderkey", words)
    if name == "passage":
        from entlink.operators.candidates import contained

        items, docs = t("benchmark"), t("documents")
        found = contained(items.select(F.col("item_id").alias("id"), "text"), docs.select(F.col("doc_id").alias("id"), "text"), hold=True)
        k = F.col("name_id").cast("string")
        pairs = found.join(items, F.col("name_id") == F.col("item_id")).select(k.alias("tuple_id"), k.alias("instance_id"), F.col("text_id").alias("doc_id"), F.col("text").alias("passage"))
        # The sentences of a document that the passage holds.
        mentions = _sentence_mentions(pairs, docs, (F.length("text") >= 20) & F.contains("passage", "text"))
        return _tuples(items, "item_id", [F.col("text")]), mentions
    if name == "page":
        pages = t("pages")
        title = F.regexp_extract("html", "<title>(.*?)</title>", 1)
        rows = paragraphs(pages)
        k = F.col("page_id").cast("string")
        mentions = rows.select(F.concat(k, F.lit("#"), F.col("no").cast("string")).alias("mention_id"), k.alias("tuple_id"), k.alias("instance_id"), F.lit("natural").alias("channel"), "text")
        return _tuples(pages, "page_id", [F.col("url"), title]), mentions
    if name == "copied-document":
        docs = t("documents")
        root = docs.groupBy(F.md5("text").alias("copy")).agg(F.min("doc_id").alias("root"), F.count("*").alias("n")).where("n > 1")
        # Copies are told by their hashes; texts are not moved for it.
        copies = materialize(docs.select("doc_id", F.md5("text").alias("copy")).join(root, "copy").select("doc_id", "root"), "copies")
        inst = F.col("root").cast("string")
        pairs = copies.where("doc_id > root").select(inst.alias("tuple_id"), inst.alias("instance_id"), "doc_id")
        rows = docs.join(held(copies.where("doc_id = root"), "roots"), "doc_id")
        mentions = _sentence_mentions(pairs, docs, F.col("sent_no") == F.pmod(F.xxhash64("doc_id"), F.lit(3)))
        return _tuples(rows, "doc_id", [F.col("lang"), F.col("source"), F.col("text")], inst), mentions
    if name == "dialogue":
        turns = t("conversations")
        k = F.col("conv_id").cast("string")
        mentions = turns.where("turn > 0").select(
            F.concat(k, F.lit("#"), F.col("turn").cast("string")).alias("mention_id"), k.alias("tuple_id"), k.alias("instance_id"), F.lit("natural").alias("channel"), "text"
        )
        return _tuples(turns.where("turn = 0"), "conv_id", [F.col("text")]), mentions
    raise ValueError(f"no entity type {name}")


#: Types whose tuples are a part of their relation's rows.
PARTIAL = ("copied-document",)
TYPE_NAMES = ("product-name", "product", "customer", "supplier", "order", "nation", "passage", "page", "copied-document", "dialogue")


def with_split(mentions: DataFrame) -> DataFrame:
    """Add ``split``: a fifth of the instances is unseen, a fifth of the other mentions is for testing."""
    unseen = h(F.concat(F.lit("u"), F.col("instance_id"))) % 5 == 0
    test = h(F.concat(F.lit("t"), F.col("mention_id"))) % 5 == 0
    return mentions.withColumn("split", F.when(unseen, "unseen").when(test, "test").otherwise("train"))


def sentences(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, sent_no, start, end, text: pieces between sentence ends and line breaks, with their offsets."""
    parts = F.split(F.coalesce(F.col(text_col), F.lit("")), r"(?<=[.!?])(?=[ \t\r\f\x0B])|\n")
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("whole"), parts.alias("parts"))
    # Pieces are disjoint and in order, so an offset is the sum of the lengths and line breaks before.
    cut = F.aggregate(
        "parts",
        F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("starts")),
        lambda acc, p: F.struct(
            (acc["at"] + F.length(p) + F.when(F.substring("whole", acc["at"] + F.length(p) + 1, F.lit(1)) == "\n", 1).otherwise(0)).alias("at"),
            F.concat(acc["starts"], F.array(acc["at"])).alias("starts"),
        ),
        lambda acc: acc["starts"],
    )
    rows = rows.select("doc_id", F.posexplode(F.arrays_zip(F.col("parts").alias("text"), cut.alias("start"))).alias("sent_no", "p"))
    return rows.select("doc_id", "sent_no", F.col("p.start").alias("start"), (F.col("p.start") + F.length("p.text")).alias("end"), F.col("p.text").alias("text")).where("trim(text) != ''")


def with_context(sents: DataFrame, before: int = 1, after: int = 1) -> DataFrame:
    """Sentences with the text of their neighbours in the document."""
    from pyspark.sql import Window

    w = Window.partitionBy("doc_id").orderBy("sent_no").rowsBetween(-before, after)
    return sents.withColumn("context", F.array_join(F.collect_list("text").over(w), " "))
