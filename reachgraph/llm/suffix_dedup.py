"""Repeated byte strings by deep-shallow suffix sorting.

A byte goes if a string of ``length`` bytes that covers it starts anywhere else,
in another text or in the same one. Texts that are equal as wholes are taken as
one first. In the others only some suffixes matter: of the ``gram``-byte pieces
in a string of ``length`` bytes, the one with the smallest hash is its anchor, so
two equal strings have their anchor at the same place. Around each anchor lies
the context that any string with this anchor is part of.

Anchors whose gram occurs once are dropped. Where whole contexts are equal the
strings in them are too. The remaining contexts of one gram are sorted twice,
by what follows the anchor and, reversed, by what precedes it: a multikey sort
goes to a shallow depth, word by word, and blind tries order the groups that
have longer common prefixes. The common prefixes of neighbours in the two orders
tell, for each place of the anchor in a string, which strings are equal.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reachgraph.llm.common import bound_batches, drop_stored, stored, sweep

LENGTH, GRAM = 200, 64
_CHUNK = 24 << 20
#: Bytes whose anchors are chosen at once; at most 2**24, as a key holds a position in 24 bits.
_SLICE = 1 << 23


# -- sorting ---------------------------------------------------------------


def common_prefix(a: bytes, b: bytes) -> int:
    """Number of leading bytes that are equal."""
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    diff = int.from_bytes(a[:n], "big") ^ int.from_bytes(b[:n], "big")
    return n - (diff.bit_length() + 7) // 8


class BlindTrie:
    """Orders strings by looking, on the way down, only at the bytes where others branch."""

    def __init__(self, strings: list[bytes]) -> None:
        self.strings = strings
        self.root: list | None = None

    def add(self, i: int) -> None:
        """Insert string ``i``. A node is [depth, branches], a leaf is [-1, members]."""
        s = self.strings[i]
        if self.root is None:
            self.root = [-1, [i]]
            return
        node = self.root
        while node[0] >= 0:
            node = node[1].get(s[node[0]] if node[0] < len(s) else -1) or next(iter(node[1].values()))
        other = self.strings[node[1][0]]
        if s == other:
            node[1].append(i)
            return
        at = common_prefix(s, other)
        above, node, edge = None, self.root, -1
        while 0 <= node[0] < at:
            edge = s[node[0]]
            above, node = node, node[1][edge]
        mine = s[at] if at < len(s) else -1
        if node[0] == at:
            node[1][mine] = [-1, [i]]
            return
        split = [at, {mine: [-1, [i]], (other[at] if at < len(other) else -1): node}]
        if above is None:
            self.root = split
        else:
            above[1][edge] = split

    def ordered(self) -> Iterator[tuple[int, int]]:
        """(string, common prefix with the one before) in order; the first has -1, equal strings their length."""
        todo: list[tuple[list, int]] = [(self.root, -1)] if self.root else []
        while todo:
            node, lcp = todo.pop()
            if node[0] < 0:
                for i in node[1]:
                    yield i, lcp
                    lcp = len(self.strings[i])
                continue
            branches = sorted(node[1].items())
            for k in range(len(branches) - 1, 0, -1):
                todo.append((branches[k][1], node[0]))
            todo.append((branches[0][1], lcp))


def deep_shallow_sort(strings: list[bytes], shallow: int = 24) -> tuple[np.ndarray, np.ndarray]:
    """(order, common prefix of each string with the one before it in order); the first has 0."""
    n = len(strings)
    if not n:
        return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
    words = shallow // 8
    head = np.frombuffer(b"".join(s[:shallow].ljust(shallow, b"\0") for s in strings), dtype=">u8").reshape(n, words).astype(np.uint64)
    size = np.fromiter((min(len(s), shallow) for s in strings), dtype=np.int64, count=n)
    # multikey: each round splits all open groups by their next eight bytes, shorter strings first
    order = np.arange(n)
    group = np.zeros(n, dtype=np.int64)
    lcp = np.zeros(n, dtype=np.int64)
    for w in range(words):
        key, ends = head[order, w], np.clip(size[order] - 8 * w, 0, 8)
        step = np.lexsort((ends, key, group))
        order, group, key, ends = order[step], group[step], key[step], ends[step]
        same = group[1:] == group[:-1]
        differ = key[1:] ^ key[:-1]
        equal = same & (differ == 0) & (ends[1:] == ends[:-1]) & (ends[1:] == 8)
        # the leading equal bytes of a word, exactly
        lead = np.zeros(len(differ), dtype=np.int64)
        for b in range(8):
            lead += (differ >> np.uint64(8 * (7 - b)) == 0).astype(np.int64)
        first = same & ~equal
        lcp[1:][first] = 8 * w + np.minimum(lead[first], np.minimum(ends[1:], ends[:-1])[first])
        # strings that end here are equal to each other; they stay in one group of their own
        done = same & (differ == 0) & (ends[1:] == ends[:-1]) & (ends[1:] < 8)
        lcp[1:][done] = size[order[1:]][done]
        group = np.concatenate([[0], np.cumsum(~(equal | done))])
    # deep: what is still together is ordered by a blind trie
    starts = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    stops = np.append(starts[1:], n)
    for a, b in zip(starts[stops - starts > 1].tolist(), stops[stops - starts > 1].tolist(), strict=True):
        members = order[a:b].tolist()
        trie = BlindTrie(strings)
        for i in members:
            trie.add(i)
        for k, (i, common) in enumerate(trie.ordered(), a):
            order[k] = i
            if common >= 0:
                lcp[k] = common
    return order, lcp


def equal_strings(contexts: list[bytes], at: np.ndarray, group: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """For each context, the least and the largest place of the anchor in a string that another context of the group has too; -1 if none.

    ``at`` is where the anchor stands in its context, ``group`` the number of its gram.
    """
    n = len(contexts)
    right = [c[p : p + length] for c, p in zip(contexts, at.tolist(), strict=True)]
    left = [g.to_bytes(4, "big") + c[:p][::-1] for c, p, g in zip(contexts, at.tolist(), group.tolist(), strict=True)]
    order_r, lcp_r = deep_shallow_sort(right)
    order_l, lcp_l = deep_shallow_sort(left)
    lcp_l = lcp_l - 4
    len_r = np.fromiter(map(len, right), dtype=np.int64, count=n)
    len_l = np.fromiter(map(len, left), dtype=np.int64, count=n) - 4
    least, most = np.full(n, -1), np.full(n, -1)
    class_r, class_l = np.empty(n, dtype=np.int64), np.empty(n, dtype=np.int64)
    for o in range(length - gram + 1):
        fit = np.flatnonzero((len_r >= length - o) & (len_l >= o))
        if len(fit) < 2:
            continue
        class_r[order_r] = np.cumsum(lcp_r < length - o)
        class_l[order_l] = np.cumsum(lcp_l < o)
        key = class_r[fit] * (n + 1) + class_l[fit]
        by = np.argsort(key, kind="stable")
        twin = key[by][1:] == key[by][:-1]
        hit = np.zeros(len(fit), dtype=bool)
        hit[by[1:][twin]] = True
        hit[by[:-1][twin]] = True
        rows = fit[hit]
        least[rows[least[rows] < 0]] = o
        most[rows] = o
    return least, most


# -- anchors ---------------------------------------------------------------


def anchors(data: np.ndarray, starts: np.ndarray, stops: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """(positions, gram hashes) of the anchors in texts that lie end to end in ``data``.

    Worked on in slices of at most ``_SLICE`` bytes, so that a position fits into
    the low bits of a key; neighbouring slices share all but one byte of a string,
    and so every string of ``length`` bytes lies in exactly one of them.
    """
    step = _SLICE - length + 1
    parts = []
    for lo in range(0, max(1, len(data) - length + 1), step):
        hi = min(len(data), lo + _SLICE)
        at, grams = _slice_anchors(data[lo:hi], starts - lo, stops - lo, length, gram)
        parts.append((at + lo, grams))
    at, first = np.unique(np.concatenate([at for at, _ in parts]), return_index=True)
    return at, np.concatenate([grams for _, grams in parts])[first]


def _slice_anchors(data: np.ndarray, starts: np.ndarray, stops: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """Anchors in a slice; ``starts`` and ``stops`` of the texts are relative to it and may lie outside."""
    n = len(data)
    if n < length:
        return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.uint64)
    h = (data.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(29)
    width, have = 1, {1: h}
    factor = {1: 0xD6E8FEB86659FD93}
    while width * 2 <= gram:
        h = h[: len(h) - width] * np.uint64(factor[width]) + h[width:]
        factor[width * 2] = factor[width] * factor[width] % 2**64
        width *= 2
        have[width] = h
    if width < gram:
        parts, got = have[width], width
        while got < gram:
            w = max(k for k in have if k <= gram - got)
            m = len(data) - got - w + 1
            parts = parts[:m] * np.uint64(factor[w]) + have[w][got : got + m]
            got += w
        h = parts
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    have.clear()
    low = np.uint64(24)
    key = ((h >> low) << low) | np.arange(len(h), dtype=np.uint64)
    window, reach = length - gram + 1, 1
    least = key
    while reach * 2 <= window:
        least = np.minimum(least[: len(least) - reach], least[reach:])
        reach *= 2
    if reach < window:
        least = np.minimum(least[: len(least) - (window - reach)], least[window - reach :])
    inside = np.zeros(len(least) + 1, dtype=np.int64)
    # texts that have a string in this slice
    long = (stops - starts >= length) & (stops - length >= 0) & (starts < len(least))
    np.add.at(inside, starts[long].clip(0), 1)
    np.add.at(inside, (stops[long] - length + 1).clip(max=len(least)), -1)
    valid = np.cumsum(inside[:-1]) > 0
    at = (least[valid] & np.uint64((1 << 24) - 1)).astype(np.int64)
    at = np.unique(at)
    return at, h[at]


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("name", pa.binary()), ("z", pa.binary())])
    press = zstandard.ZstdCompressor(level=3)
    for batch in batches:
        z = [press.compress(t.as_buffer()) for t in batch.column("text").cast(pa.binary())]
        yield pa.RecordBatch.from_arrays([batch.column("name"), pa.array(z, type=pa.binary())], schema=schema)


def _anchors(length: int, gram: int):
    schema = pa.schema([("gram", pa.int64()), ("context", pa.int64()), ("tid", pa.int64()), ("pos", pa.int32())])

    def some(ids: list[int], texts: list[bytes]) -> pa.RecordBatch:
        whole = b"".join(texts)
        stops = np.cumsum([len(t) for t in texts])
        starts = stops - [len(t) for t in texts]
        at, grams = anchors(np.frombuffer(whole, dtype=np.uint8), starts, stops, length, gram)
        text = np.searchsorted(stops, at, side="right")
        lo = np.maximum(starts[text], at - (length - gram))
        hi = np.minimum(stops[text], at + length)
        digest = xxhash.xxh3_64_intdigest
        context = [digest(whole[a:b], s) for a, b, s in zip(lo.tolist(), hi.tolist(), (at - lo).tolist(), strict=True)]
        columns = [grams.view(np.int64), np.array(context, dtype=np.uint64).view(np.int64), np.array(ids, dtype=np.int64)[text] if ids else text, (at - starts[text]).astype(np.int32) if ids else text]
        return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor()
        ids, texts, total = [], [], 0
        for batch in batches:
            for tid, z in zip(batch.column("tid").to_pylist(), batch.column("z"), strict=True):
                text = unpack.decompress(z.as_buffer())
                ids.append(tid)
                texts.append(text)
                total += len(text)
                if total > 1 << 20:
                    yield some(ids, texts)
                    ids, texts, total = [], [], 0
        if ids:
            yield some(ids, texts)

    return run


def _contexts(length: int, gram: int):
    schema = pa.schema([("gram", pa.int64()), ("tid", pa.int64()), ("pos", pa.int32()), ("at", pa.int32()), ("alone", pa.bool_()), ("hot", pa.bool_()), ("bytes", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            rows: list[tuple] = []
            for tid, z, wanted in zip(batch.column("tid").to_pylist(), batch.column("z"), batch.column("wanted").to_pylist(), strict=True):
                text = unpack.decompress(z.as_buffer())
                for w in wanted:
                    lo = max(0, w["pos"] - (length - gram))
                    rows.append((w["gram"], tid, w["pos"], w["pos"] - lo, w["alone"], w["hot"], text[lo : w["pos"] + length]))
                    if len(rows) >= 20_000:
                        yield _rows(rows, schema)
                        rows = []
            yield _rows(rows, schema)

    return run


def _rows(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [[]] * len(schema)
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


_SPANS = pa.schema([("tid", pa.int64()), ("lo", pa.int32()), ("hi", pa.int32())])


def _compare(length: int, gram: int):
    def some(rows: list[tuple]) -> pa.RecordBatch:
        grams = [r[0] for r in rows]
        group = np.unique(np.array(grams, dtype=np.int64), return_inverse=True)[1]
        least, most = equal_strings([r[5] for r in rows], np.array([r[3] for r in rows], dtype=np.int64), group, length, gram)
        out = [(r[1], r[2] - b, r[2] - a + length) for r, a, b in zip(rows, least.tolist(), most.tolist(), strict=True) if a >= 0 and r[4]]
        return _rows(out, _SPANS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        total, last = 0, None
        for batch in batches:
            for r in zip(*(batch.column(c).to_pylist() for c in ("gram", "tid", "pos", "at", "alone", "bytes")), strict=True):
                if r[0] != last and total > _CHUNK:
                    yield some(rows)
                    rows, total = [], 0
                last = r[0]
                rows.append(r)
                total += len(r[5]) + 200
        if rows:
            yield some(rows)

    return run


def _strings(length: int, gram: int):
    """Hash of every string around an anchor, with its place, for grams with too many contexts for one task."""
    schema = pa.schema([("h1", pa.int64()), ("h2", pa.int64()), ("tid", pa.int64()), ("lo", pa.int32()), ("alone", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            for gram_hash, tid, pos, at, alone, data in zip(*(batch.column(c).to_pylist() for c in ("gram", "tid", "pos", "at", "alone", "bytes")), strict=True):
                for s in range(max(0, at + gram - length), min(at, len(data) - length) + 1):
                    # the anchor and its place belong to the key: other anchors see the same string
                    d = xxhash.xxh3_128_digest(data[s : s + length], (gram_hash + 31 * (at - s)) % 2**64)
                    rows.append((int.from_bytes(d[:8], "big", signed=True), int.from_bytes(d[8:], "big", signed=True), tid, pos - at + s, alone))
                if len(rows) >= 20_000:
                    yield _rows(rows, schema)
                    rows = []
            yield _rows(rows, schema)

    return run


def merge_spans(spans: list[tuple[int, int]], size: int) -> list[tuple[int, int]]:
    """Maximal runs that the spans cover within ``size`` bytes."""
    out: list[tuple[int, int]] = []
    for lo, hi in sorted((max(0, a), min(size, b)) for a, b in spans):
        if out and lo <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], hi))
        elif lo < hi:
            out.append((lo, hi))
    return out


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("name", pa.binary()), ("spans", pa.list_(pa.list_(pa.int64()))), ("kept_sha256", pa.string())])
    unpack = zstandard.ZstdDecompressor()
    for batch in batches:
        rows = []
        for name, z, spans in zip(batch.column("name").to_pylist(), batch.column("z"), batch.column("spans").to_pylist(), strict=True):
            text = unpack.decompress(z.as_buffer())
            runs = merge_spans([(s["lo"], s["hi"]) for s in spans], len(text))
            left, at = hashlib.sha256(), 0
            for lo, hi in runs:
                left.update(text[at:lo])
                at = hi
            left.update(text[at:])
            rows.append((name, [list(r) for r in runs], left.hexdigest()))
        yield _rows(rows, schema)


# -- the operator ----------------------------------------------------------


def repeated_strings(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, gram: int = GRAM, group_rows: int = 50_000
) -> DataFrame:
    """doc_id, n_bytes, spans, kept_sha256: one row per input row.

    ``spans`` are the maximal runs of removed bytes, as [start, end) pairs in
    order; ``kept_sha256`` is the digest of the bytes between them. Null texts
    are empty. Null ids and repeated rows are rows like any other, and the texts
    of repeated rows repeat. Texts shorter than ``length`` lose nothing. A gram
    with more than ``group_rows`` different contexts is settled by hashes of all
    strings around it, counted in a partial aggregation, and not in one task.
    Other columns are not read; an empty table gives an empty result.
    """
    spark = docs.sparkSession
    bound_batches(spark)
    text = F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.unhex(F.md5(text)).alias("name"), F.octet_length(text).cast("long").alias("n_bytes"), text.alias("text"))
    listed = stored(rows.select("doc_id", "name", "n_bytes", F.sha2("text", 256).alias("whole")), "listed")
    packed = rows.where(F.col("n_bytes") >= length).select("name", "text").mapInArrow(_pack, "name binary, z binary")
    texts = packed.groupBy("name").agg(F.first("z").alias("z"), F.count(F.lit(1)).alias("copies"))
    texts = stored(texts.withColumn("tid", F.monotonically_increasing_id()), "texts")
    sweep(spark)
    found = stored(texts.select("tid", "z").mapInArrow(_anchors(length, gram), "gram long, context long, tid long, pos int"), "anchors")
    often = found.groupBy("gram").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("gram")
    met = stored(found.join(often, "gram"), "met")
    drop_stored(found)
    sweep(spark)
    # equal contexts: all strings in them are repeated
    contexts = met.groupBy("gram", "context").agg(F.count(F.lit(1)).alias("m"), F.min(F.struct("tid", "pos")).alias("one"))
    contexts = stored(contexts, "contexts")
    same = met.join(contexts.where("m > 1").select("gram", "context"), ["gram", "context"])
    spans = same.select("tid", (F.col("pos") - F.lit(length - gram)).cast("int").alias("lo"), (F.col("pos") + F.lit(length)).cast("int").alias("hi"))
    spans = spans.groupBy("tid", "lo", "hi").count().select("tid", "lo", "hi")
    # different contexts of one gram
    open_ = contexts.groupBy("gram").agg(F.count(F.lit(1)).alias("n"), F.min("m").alias("least")).where("n > 1 and least = 1")
    open_ = open_.select("gram", (F.col("n") > group_rows).alias("hot"))
    wanted = contexts.join(open_, "gram").select(F.col("one.tid").alias("tid"), F.col("one.pos").alias("pos"), "gram", (F.col("m") == 1).alias("alone"), "hot")
    wanted = wanted.groupBy("tid").agg(F.collect_list(F.struct("pos", "gram", "alone", "hot")).alias("wanted"))
    cut = wanted.join(texts.select("tid", "z"), "tid").mapInArrow(_contexts(length, gram), "gram long, tid long, pos int, at int, alone boolean, hot boolean, bytes binary")
    cut = stored(cut, "cut")
    sweep(spark)
    cold = cut.where("not hot").repartition("gram").sortWithinPartitions("gram").mapInArrow(_compare(length, gram), "tid long, lo int, hi int")
    strings = cut.where("hot").mapInArrow(_strings(length, gram), "h1 long, h2 long, tid long, lo int, alone boolean")
    twice = strings.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h1", "h2")
    hot = strings.where("alone").join(twice, ["h1", "h2"]).select("tid", "lo", (F.col("lo") + F.lit(length)).cast("int").alias("hi"))
    spans = spans.unionByName(cold).unionByName(hot)
    by_text = spans.groupBy("tid").agg(F.collect_list(F.struct("lo", "hi")).alias("spans"))
    cutting = by_text.join(texts.where("copies = 1").select("tid", "name", "z"), "tid").select("name", "z", "spans")
    result = cutting.mapInArrow(_cut, "name binary, spans array<array<long>>, kept_sha256 string")
    result = stored(result.unionByName(texts.where("copies > 1").select("name", F.lit(None).cast("array<array<long>>").alias("spans"), F.lit("").alias("kept_sha256"))), "cuts")
    sweep(spark)
    all_of_it = F.array(F.array(F.lit(0).cast("long"), F.col("n_bytes")))
    nothing = F.array().cast("array<array<long>>")
    joined = listed.join(result.withColumn("hit", F.lit(True)), "name", "left")
    copy = F.col("hit").isNotNull() & F.col("spans").isNull()
    return joined.select(
        "doc_id",
        "n_bytes",
        F.when(F.col("hit").isNull(), nothing).when(copy, all_of_it).otherwise(F.col("spans")).alias("spans"),
        F.when(F.col("hit").isNull(), F.col("whole")).when(copy, F.lit(hashlib.sha256().hexdigest())).otherwise(F.col("kept_sha256")).alias("kept_sha256"),
    )
