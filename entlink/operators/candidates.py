"""Candidate search: equal, contained, shared-word, gold, and unions with provenance.

Every strategy is an equi join on something rare, with the real predicate as
residual; none enumerates all pairs.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from entlink.functions.text import h, tokens
from entlink.operators.ordering import ranked
from entlink.storage import held, materialize, measured_broadcasts


def equal(names: DataFrame, texts: DataFrame) -> DataFrame:
    """``(name_id, text_id)`` of strings equal after trimming and lower-casing; inputs are (id, text)."""
    key = F.lower(F.trim("text"))
    return names.select(F.col("id").alias("name_id"), key.alias("k")).join(texts.select(F.col("id").alias("text_id"), key.alias("k")), "k").select("name_id", "text_id")


EDGE = 3  # characters of cut tokens that serve as keys


def contained(names: DataFrame, texts: DataFrame, hold: bool = False) -> DataFrame:
    """``(name_id, text_id)`` where the whole name occurs in the text; inputs are (id, text).

    A name's first and last token may be part of longer ones in the text, so keys are what must stand there whole:
    the rarest of the tokens between them; for two tokens the end of the first with the beginning of the second; for
    one token the words of the texts that hold it, found by their runs of letters; for names without letters or digits
    their first character.  An empty name occurs nowhere.

    With ``hold`` keys are looked up at once, and where they are few they are sent to the texts (``storage.held``), so
    that neither the words of the texts nor texts without a key are moved.
    """
    measured_broadcasts(names.sparkSession)
    t = tokens(F.col("text"))
    named = names.where(F.length("text") > 0).select(F.col("id").alias("name_id"), F.col("text").alias("name"), t.alias("t"))
    read = texts.select(F.col("id").alias("text_id"), t.alias("t"))
    words = read.select("text_id", F.explode(F.array_distinct("t")).alias("token"))
    n = F.least(F.size("t"), F.lit(3))
    sizes = [r.n for r in named.select(n.alias("n")).distinct().collect()] or [3] if hold else range(4)  # four at most
    keep = held if hold else lambda df, tag: df
    search = {
        3: lambda own: _by_inner_token(own, words, keep),
        2: lambda own: _by_adjacent_ends(own, read, keep),
        1: lambda own: _by_word_part(own, words, keep),
        0: lambda own: _by_character(own, texts, keep),
    }
    hits = reduce(DataFrame.unionByName, [search[k](named.where(n == k)) for k in sorted(sizes, reverse=True)]).distinct()
    if hold:
        hits = materialize(hits, "hits")
        texts = texts.join(held(hits.select(F.col("text_id").alias("id")).distinct(), "hit-texts"), "id", "left_semi")
    whole = hits.join(named.select("name_id", "name"), "name_id").join(texts.select(F.col("id").alias("text_id"), "text"), "text_id")
    return whole.where(F.contains("text", "name")).select("name_id", "text_id")


Keep = Callable[[DataFrame, str], DataFrame]  # what becomes of keys that meet all texts


def _by_inner_token(named: DataFrame, words: DataFrame, keep: Keep) -> DataFrame:
    inner = named.select("name_id", F.explode(F.array_distinct(F.slice("t", F.lit(2), F.greatest(F.size("t") - 2, F.lit(0))))).alias("token"))
    return keep(_rarest(inner, words, keep), "rarest").join(words, "token").select("name_id", "text_id")


def _rarest(name_tokens: DataFrame, words: DataFrame, keep: Keep = lambda df, tag: df) -> DataFrame:
    """``(name_id, token)``: the token of each name that stands in the fewest texts, of equals the first by spelling."""
    df = words.join(keep(name_tokens.select("token").distinct(), "name-tokens"), "token", "left_semi").groupBy("token").agg(F.count("*").alias("df"))
    best = F.row_number().over(Window.partitionBy("name_id").orderBy("df", "token"))
    return name_tokens.join(df, "token").withColumn("n", best).where("n = 1").select("name_id", "token")


def _by_adjacent_ends(named: DataFrame, read: DataFrame, keep: Keep) -> DataFrame:
    ends = lambda left, right, a, b: F.concat_ws(" ", F.lit(f"{a}{b}"), F.substring(left, -a, a), F.substring(right, 1, b))
    sides = [F.least(F.length(F.get("t", F.lit(i))), F.lit(EDGE)) for i in (0, 1)]
    out = None
    for a in range(1, EDGE + 1):
        for b in range(1, EDGE + 1):
            # Names whose tokens have fewer characters than the edge are keyed by as many as they have.
            own = named.where((sides[0] == a) & (sides[1] == b)).select("name_id", ends(F.get("t", F.lit(0)), F.get("t", F.lit(1)), a, b).alias("key"))
            out = own if out is None else out.unionByName(own)
    forms = [(a, b) for a in range(1, EDGE + 1) for b in range(1, EDGE + 1)]
    pairs = lambda a, b: F.transform(F.sequence(F.lit(1), F.size("t") - 1), lambda i: ends(F.get("t", i - 1), F.get("t", i), a, b))
    wanted = {(r.a, r.b) for r in named.select(sides[0].alias("a"), sides[1].alias("b")).distinct().collect()}  # nine at most
    if not wanted:
        return named.select("name_id", F.lit(None).cast(read.schema["text_id"].dataType).alias("text_id")).where("false")
    every = F.array_distinct(F.concat(*[pairs(a, b) for a, b in forms if (a, b) in wanted]))
    seen = read.where(F.size("t") > 1).select("text_id", F.explode(every).alias("key"))
    return keep(out, "ends").join(seen, "key").select("name_id", "text_id")


def _grams(word) -> Column:
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length(word) - EDGE + 1, F.lit(1))), lambda i: F.substring(word, i, F.lit(EDGE))))


def _by_word_part(named: DataFrame, words: DataFrame, keep: Keep) -> DataFrame:
    one = named.select("name_id", F.get("t", F.lit(0)).alias("part"))
    vocabulary = words.select("token").distinct()
    long = one.where(F.length("part") >= EDGE).withColumn("gram", F.substring("part", 1, EDGE))
    grams = vocabulary.select("token", F.explode(_grams(F.col("token"))).alias("gram"))
    short = one.where(F.length("part") < EDGE).withColumn("gram", F.col("part"))
    parts = lambda n: F.transform(F.sequence(F.lit(1), F.length("token")), lambda i: F.substring("token", i, F.lit(n)))
    pieces = F.array_distinct(F.flatten(F.array(*[parts(n) for n in range(1, EDGE)])))
    small = vocabulary.select("token", F.explode(pieces).alias("gram"))
    found = long.join(grams, "gram").unionByName(short.join(small, "gram")).where(F.contains("token", "part"))
    return keep(found.select("name_id", "token").distinct(), "parts").join(words, "token").select("name_id", "text_id")


def _by_character(named: DataFrame, texts: DataFrame, keep: Keep) -> DataFrame:
    signs = F.array_distinct(F.split(F.regexp_replace(F.coalesce("text", F.lit("")), r"[\p{L}\p{N}]", ""), ""))
    seen = texts.select(F.col("id").alias("text_id"), F.explode(signs).alias("sign")).where("sign != ''")
    return keep(named.select("name_id", F.substring("name", 1, 1).alias("sign")), "signs").join(seen, "sign").select("name_id", "text_id")


def blocks(names: DataFrame, texts: DataFrame) -> DataFrame:
    """``(name_id, text_id)`` of each name and the texts that hold its rarest word: a name's block."""
    measured_broadcasts(names.sparkSession)
    t = F.array_distinct(tokens(F.col("text")))
    words = texts.select(F.col("id").alias("text_id"), F.explode(t).alias("token"))
    own = names.select(F.col("id").alias("name_id"), F.explode(t).alias("token"))
    return _rarest(own, words).join(words, "token").select("name_id", "text_id")


def shared_word(names: DataFrame, texts: DataFrame, min_overlap: int = 1, max_df: int | None = None) -> DataFrame:
    """``(name_id, text_id, shared)``: pairs with at least ``min_overlap`` tokens in common, leaving out tokens
    that stand in more than ``max_df`` texts."""
    measured_broadcasts(names.sparkSession)
    a = names.select(F.col("id").alias("name_id"), F.explode(F.array_distinct(tokens(F.col("text")))).alias("token"))
    b = texts.select(F.col("id").alias("text_id"), F.explode(F.array_distinct(tokens(F.col("text")))).alias("token"))
    if max_df is not None:
        rare = b.groupBy("token").agg(F.count("*").alias("df")).where(F.col("df") <= max_df)
        a = a.join(rare.select("token"), "token", "left_semi")
    return a.join(b, "token").groupBy("name_id", "text_id").agg(F.count("*").alias("shared")).where(F.col("shared") >= min_overlap)


def detect(sents: DataFrame, names: DataFrame, max_words: int = 4) -> DataFrame:
    """Dictionary mentions: spans of up to ``max_words`` tokens equal to an entity name.

    Returns name_id, doc_id, sent_no, first token number and number of tokens.
    """
    measured_broadcasts(names.sparkSession)
    t = sents.select("doc_id", "sent_no", tokens(F.col("text")).alias("t"))
    starts = t.select("doc_id", "sent_no", "t", F.explode(F.sequence(F.lit(1), F.size("t"))).alias("at")).where(F.size("t") > 0)
    grams = starts.select("doc_id", "sent_no", "at", F.explode(F.sequence(F.lit(1), F.least(F.lit(max_words), F.size("t") - F.col("at") + 1))).alias("words"), "t")
    grams = grams.select("doc_id", "sent_no", (F.col("at") - 1).alias("token_no"), "words", F.array_join(F.slice("t", F.col("at"), F.col("words")), " ").alias("said"))
    keys = names.select(F.col("id").alias("name_id"), F.array_join(tokens(F.col("text")), " ").alias("said"))
    return grams.join(keys, "said").select("name_id", "doc_id", "sent_no", "token_no", "words")


def union_of(pools: dict[str, DataFrame]) -> DataFrame:
    """``(name_id, text_id, strategies)``: every pair once, with the sorted names of the strategies that found it."""
    marked = [df.select("name_id", "text_id").withColumn("s", F.lit(k)) for k, df in pools.items()]
    return reduce(DataFrame.unionByName, marked).groupBy("name_id", "text_id").agg(F.sort_array(F.collect_set("s")).alias("strategies"))


def non_matches(names: DataFrame, texts: DataFrame, gold: DataFrame, n_per: int = 2) -> DataFrame:
    """Negatives for each name: the texts whose hash follows the name's in hash order, unless gold."""
    hashed = texts.select(F.col("id").alias("text_id"), h(F.col("id").cast("string")).alias("hash"))
    order, total = ranked(hashed, ["hash", "text_id"], "at", "negatives")
    picks = names.select(F.col("id").alias("name_id"), F.explode(F.sequence(F.lit(1), F.lit(n_per))).alias("i"))
    picks = picks.withColumn("at", h(F.concat(F.col("name_id").cast("string"), F.lit("#"), F.col("i").cast("string"))) % max(1, total))
    return picks.join(order, "at").select("name_id", "text_id").distinct().join(gold, ["name_id", "text_id"], "left_anti")
