"""Mixing sources to target weights by balanced (cube) sampling.

Each source gets a target number of words; every document of the source has
the same inclusion rate ``target / source_size``. The whole part of the rate is
taken for certain, the rest is an inclusion probability. The flight phase moves
the probabilities of three documents at a time along the null space of the two
balancing rows (words, documents), so that both totals stay as they are, until
one of the three is decided. Blocks of a bounded number of documents fly in
parallel and leave at most two undecided documents each; these meet in the next
round. A round divides their number by ``block / 2``, so there are
``log(n) / log(block / 2)`` rounds and a hot source is spread over as many blocks
as it needs. When a source is down to one block, the landing phase gives up the
document total, then the word total. Large documents fly first, so what is left
to land is the smallest of them.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reachgraph.llm.common import stored, word_count

#: The weights of the sources in code-point order, repeating.
WEIGHTS = (3.0, 1.0, 2.0)


def fill_targets(sizes: list[int], weights: list[float], share: float, most: float) -> list[float]:
    """Targets that share ``share`` of all sizes by weight, none above ``most`` times its source.

    What a stopped target leaves is dealt again by weight among the others.
    """
    total = share * sum(sizes)
    targets = [0.0] * len(sizes)
    open_ = [i for i, s in enumerate(sizes) if s > 0]
    while open_:
        left = total - sum(targets[i] for i in range(len(sizes)) if i not in set(open_))
        per = left / sum(weights[i] for i in open_)
        over = [i for i in open_ if per * weights[i] > most * sizes[i]]
        for i in over or open_:
            targets[i] = most * sizes[i] if over else per * weights[i]
        if not over:
            break
        open_ = [i for i in open_ if i not in set(over)]
    return targets


def _coin(seed: int, *parts: object) -> float:
    """A reproducible number in [0, 1)."""
    digest = hashlib.blake2b(repr((seed, *parts)).encode(), digest_size=8).digest()
    return int.from_bytes(digest, "big") / 2**64


def fly(sizes: list[int], probs: list[float], seed: int, label: str, land: bool) -> list[float]:
    """Decide documents (probability 0 or 1) while the balancing totals stay fixed.

    At most two stay undecided; with ``land`` none does.
    """
    probs = list(probs)
    tiny = 1e-9
    todo = [i for i, p in enumerate(probs) if tiny < p < 1 - tiny]
    todo.reverse()
    held: list[int] = []
    step = 0
    while True:
        while len(held) < 3 and todo:
            held.append(todo.pop())
        n = len(held)
        if n < 3 and not land or n == 0:
            break
        s = [float(sizes[i]) for i in held]
        if n == 3:
            u = [s[1] - s[2], s[2] - s[0], s[0] - s[1]]
            if not any(u):
                u = [1.0, -1.0, 0.0]
        elif n == 2:
            u = [s[1], -s[0]] if any(s) else [1.0, -1.0]
        else:
            u = [1.0]
        up = min((1 - probs[i]) / v if v > 0 else probs[i] / -v for i, v in zip(held, u, strict=True) if v)
        down = min(probs[i] / v if v > 0 else (1 - probs[i]) / -v for i, v in zip(held, u, strict=True) if v)
        step += 1
        move = up if _coin(seed, label, step) * (up + down) < down else -down
        for i, v in zip(held, u, strict=True):
            p = probs[i] + move * v
            probs[i] = 0.0 if p < tiny else 1.0 if p > 1 - tiny else p
        held = [i for i in held if 0.0 < probs[i] < 1.0]
    return [0.0 if p <= tiny else 1.0 if p >= 1 - tiny else p for p in probs]


def _flight(seed: int, turn: int, land: bool):
    def run(key: tuple, rows: pa.Table) -> pa.Table:
        rows = rows.sort_by([("size", "descending"), ("doc_id", "ascending"), ("tie", "ascending")])
        label = f"{key[0].as_py()}/{key[1].as_py()}/{turn}"
        probs = fly(rows["size"].to_pylist(), rows["prob"].to_pylist(), seed, label, land)
        return rows.set_column(rows.schema.get_field_index("prob"), "prob", pa.array(probs, type=pa.float64()))

    return run


def mix_sources(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    weights: tuple[float, ...] = WEIGHTS,
    share: float = 1.5,
    most: float = 2.0,
    block: int = 256,
    seed: int = 7,
    max_sources: int = 100_000,
) -> DataFrame:
    """doc_id, source, size, source_size, target, taken, copies, tie: one row per input row; ``tie`` is the hash of the text.

    Null or empty texts have size 0 and take nothing. A null source is a source
    of its own, ordered last; null ids and repeated rows are rows like any other.
    An empty table gives an empty result. Columns beyond the three named ones are
    not read, so clashing names do no harm. ``max_sources`` bounds the mixture
    table that the driver holds; more sources are an error, never cut off.
    """
    spark = docs.sparkSession
    sizes = stored(
        docs.select(
            F.col(id_col).cast("long").alias("doc_id"),
            F.col(source_col).cast("string").alias("source"),
            word_count(F.col(text_col)).alias("size"),
            F.coalesce(F.xxhash64(F.col(text_col)), F.lit(0).cast("long")).alias("tie"),
        ),
        "sizes",
    )
    totals = sizes.groupBy("source").agg(F.sum("size").alias("total"), F.count(F.lit(1)).alias("rows"))
    totals = totals.limit(max_sources + 1).collect()
    if len(totals) > max_sources:
        raise ValueError(f"more than {max_sources} sources; name fewer sources or raise max_sources")
    totals.sort(key=lambda r: (r.source is None, r.source or ""))
    targets = fill_targets([r.total for r in totals], [weights[i % len(weights)] for i in range(len(totals))], share, most)
    mixture = spark.createDataFrame(
        [(r.source, int(r.total), float(t), max(1, -(-r.rows // block))) for r, t in zip(totals, targets, strict=True)],
        "source string, source_size long, target double, blocks long",
    )
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    rated = (
        sizes.join(F.broadcast(mixture), sizes["source"].eqNullSafe(mixture["source"]))
        .drop(mixture["source"])
        .withColumn("whole", F.floor(rate + F.lit(1e-12)))
        .withColumn("prob", F.greatest(F.lit(0.0), rate - F.col("whole")))
    )
    keep = ["doc_id", "source", "size", "tie", "source_size", "target", "blocks", "whole", "prob"]
    rows = rated.select(*keep)
    done: list[DataFrame] = []
    most_blocks = max((-(-r.rows // block) for r in totals), default=1)
    turn = 0
    while True:
        last = most_blocks <= 1
        slot = F.pmod(F.xxhash64("doc_id", "tie", F.lit(turn)), F.col("blocks"))
        flown = (
            rows.withColumn("slot", slot)
            .groupBy("source", "slot")
            .applyInArrow(_flight(seed, turn, last), rows.withColumn("slot", slot).schema)
            .drop("slot")
        )
        if last:
            done.append(flown)
            break
        flown = stored(flown, "flown")
        open_ = (F.col("prob") > 0) & (F.col("prob") < 1)
        done.append(flown.where(~open_))
        # at most two per block remain
        shrink = F.greatest(F.lit(1), F.ceil(2 * F.col("blocks") / F.lit(block)))
        rows = flown.where(open_).withColumn("blocks", shrink.cast("long"))
        most_blocks = -(-2 * most_blocks // block)
        turn += 1
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    copies = (F.col("whole") + F.col("prob")).cast("long")
    return out.select(
        "doc_id", "source", "size", "source_size", "target", (copies * F.col("size")).alias("taken"), copies.alias("copies"), "tie"
    )


def keep_mixed(docs: DataFrame, **options: object) -> DataFrame:
    """The documents that the mix takes, with all their columns and how often it takes them.

    ``mix_copies`` is the number of times, ``mix_target`` the target of the
    source. Repeated rows become one, with the copies of all of them. A column
    of ``docs`` that has one of these two names gives way.
    """
    id_col, text_col = str(options.get("id_col", "doc_id")), str(options.get("text_col", "text"))
    taken = mix_sources(docs, **options).where("copies > 0").groupBy(F.col("doc_id").alias("_id"), F.col("tie").alias("_tie"))
    taken = taken.agg(F.sum("copies").alias("mix_copies"), F.max("target").alias("mix_target"))
    rows = docs.drop("mix_copies", "mix_target").withColumn("_text", F.coalesce(F.xxhash64(F.col(text_col)), F.lit(0).cast("long")))
    same = rows[id_col].cast("long").eqNullSafe(taken["_id"]) & (rows["_text"] == taken["_tie"])
    return rows.join(taken.hint("shuffle_hash"), same).dropDuplicates([id_col, "_text"]).drop("_id", "_tie", "_text")
