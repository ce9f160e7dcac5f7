"""Ids of table rows and literals, as native columns."""

from __future__ import annotations

import xxhash
from pyspark.sql import Column
from pyspark.sql import functions as F

#: The kind in the upper bits of an id.
KINDS = {"region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "order": 6, "event": 7, "user": 8, "document": 9, "benchmark": 10, "page": 11, "vector": 12, "conversation": 13, "turn": 14, "literal": 15}
SHIFT = 48
BASE = 1 << SHIFT


def term_id(kind: str, key: Column | str) -> Column:
    """Id of a table row; null where the key is null."""
    col = F.col(key) if isinstance(key, str) else key
    return F.lit(KINDS[kind] * BASE) + col.cast("long")


def literal_id(text: Column | str) -> Column:
    """Id of a literal: 48 bits of a hash of its text; ``dictionary`` audits collisions."""
    col = F.col(text) if isinstance(text, str) else text
    return F.when(col.isNotNull(), F.lit(KINDS["literal"] * BASE) + F.pmod(F.xxhash64(col.cast("string")), F.lit(BASE)))


def literal_number(text: str) -> int:
    """What ``literal_id`` gives for one text, without a job: the same hash with Spark's seed."""
    return KINDS["literal"] * BASE + xxhash.xxh64_intdigest(text.encode(), seed=42) % BASE


def term_key(term: Column | str) -> Column:
    """The key of the row that an id names."""
    col = F.col(term) if isinstance(term, str) else term
    return F.pmod(col, F.lit(BASE)).cast("long")


def term_text(term: Column | str) -> Column:
    """``kind/key`` of an id."""
    col = F.col(term) if isinstance(term, str) else term
    names = F.create_map(*[F.lit(x) for k, v in KINDS.items() for x in (v, k)])
    return F.concat_ws("/", names[F.shiftright(col, SHIFT).cast("int")], term_key(col).cast("string"))
