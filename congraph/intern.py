"""Class ids: a 7-bit namespace above a 56-bit key, so that natural integer keys need no dictionary.

Text keys are hashed into the 56 bits; `hash_collisions` finds the ones that meet. Ids are a function of their
key alone, so a recomputed task gives the same ones.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KEY_BITS = 56
#: Order fixes the tags; append only.
NAMESPACES = (
    "node", "part", "order", "customer", "supplier", "nation", "region", "line", "item", "ship", "value", "doc", "source", "lang",
    "user", "type", "chain", "text", "role", "vec", "label", "cell", "bench", "class", "date", "word", "page",
)
_KEY_MASK = (1 << KEY_BITS) - 1


def tag(namespace: str) -> int:
    return NAMESPACES.index(namespace) + 1


def key_id(namespace: str, key: Column) -> Column:
    """Id of a natural key from 0 to 2^56 - 1."""
    return F.lit(tag(namespace) << KEY_BITS).cast("long") + key.cast("long")


def hash_id(namespace: str, *keys: Column) -> Column:
    return F.lit(tag(namespace) << KEY_BITS).cast("long") + F.xxhash64(*keys).bitwiseAND(F.lit(_KEY_MASK))


def constant_id(namespace: str, key: int) -> int:
    return (tag(namespace) << KEY_BITS) + key


def key_of(id_: Column) -> Column:
    """The natural key behind an id of `key_id`."""
    return id_.bitwiseAND(F.lit(_KEY_MASK))


def hash_collisions(keys: DataFrame, id_col: str, key_col: str) -> DataFrame:
    """Ids that several keys share."""
    return keys.groupBy(id_col).agg(F.count_distinct(key_col).alias("keys")).where("keys > 1")
