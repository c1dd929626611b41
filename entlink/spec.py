"""Description of an entity relation: key, instance, typed attributes, foreign keys."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import types as T

TEXT, NUMBER, ONE_HOT = "text", "number", "one_hot"


def codec_of(kind: T.DataType) -> str:
    """Text, number or one-hot by SQL type: everything that is neither string nor numeric is one-hot."""
    if isinstance(kind, (T.StringType, T.CharType, T.VarcharType)):
        return TEXT
    return NUMBER if isinstance(kind, T.NumericType) else ONE_HOT


@dataclass(frozen=True)
class ForeignKey:
    """Column of this relation whose value is the key of rows in another one."""

    column: str
    target: EntitySpec
    target_key: str


@dataclass(frozen=True)
class EntitySpec:
    name: str
    table: str
    key: str
    instance: str
    attributes: dict[str, str]  # column to codec, in block order
    foreign_keys: tuple[ForeignKey, ...] = field(default=())

    @classmethod
    def infer(cls, name: str, table: str, schema: T.StructType, key: str, instance: str, overrides: dict[str, str] | None = None,
              foreign_keys: tuple[ForeignKey, ...] = ()) -> EntitySpec:
        """Dispatch every column but the keys by type; ``overrides`` wins, and a codec of None leaves a column out."""
        taken = {key, *(f.column for f in foreign_keys)}
        codecs = {f.name: (overrides or {}).get(f.name, codec_of(f.dataType)) for f in schema if f.name not in taken or f.name in (overrides or {})}
        return cls(name, table, key, instance, {c: k for c, k in codecs.items() if k}, foreign_keys)


REGION = EntitySpec("region", "region", "r_regionkey", "r_regionkey", {"r_name": TEXT})
NATION = EntitySpec("nation", "nation", "n_nationkey", "n_nationkey", {"n_name": TEXT}, (ForeignKey("n_regionkey", REGION, "r_regionkey"),))
PART = EntitySpec("product-name", "part", "p_partkey", "p_name", {"p_name": TEXT, "p_brand": ONE_HOT, "p_type": TEXT, "p_size": NUMBER, "p_retailprice": NUMBER})
PRODUCT = EntitySpec("product", "part", "p_partkey", "p_partkey", PART.attributes)
CUSTOMER = EntitySpec(
    "customer", "customer", "c_custkey", "c_custkey", {"c_name": TEXT, "c_acctbal": NUMBER, "c_mktsegment": ONE_HOT}, (ForeignKey("c_nationkey", NATION, "n_nationkey"),)
)
SUPPLIER = EntitySpec("supplier", "supplier", "s_suppkey", "s_suppkey", {"s_name": TEXT, "s_acctbal": NUMBER}, (ForeignKey("s_nationkey", NATION, "n_nationkey"),))
ORDER = EntitySpec(
    "order", "orders", "o_orderkey", "o_orderkey", {"o_orderkey": TEXT, "o_orderstatus": ONE_HOT, "o_totalprice": NUMBER, "o_orderpriority": ONE_HOT}, (ForeignKey("o_custkey", CUSTOMER, "c_custkey"),)
)
PASSAGE = EntitySpec("passage", "benchmark", "item_id", "item_id", {"text": TEXT})
PAGE = EntitySpec("page", "pages", "page_id", "page_id", {"url": TEXT, "title": TEXT})
COPIED = EntitySpec("copied-document", "documents", "doc_id", "doc_id", {"text": TEXT, "lang": ONE_HOT, "source": ONE_HOT, "n_chars": NUMBER})
# The relation of a dialogue holds its first turn; see ``sources.mentions.relations``.
DIALOGUE = EntitySpec("dialogue", "conversations", "conv_id", "conv_id", {"text": TEXT})
TYPES = (PART, PRODUCT, CUSTOMER, SUPPLIER, ORDER, NATION, PASSAGE, PAGE, COPIED, DIALOGUE)
BY_NAME = {s.name: s for s in TYPES}
