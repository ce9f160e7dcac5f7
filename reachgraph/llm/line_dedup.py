"""Near-duplicate lines by a segment-partition edit join, in DataFrame functions only.

A line is a row of units: its words where it has enough of them, else its
characters. How many edits of a unit two lines may be apart grows with their
length. The shorter line is cut into threshold + 1 segments. Two lines within
the threshold share at least one segment that no edit touches, so each line is
indexed by its segments (length of the line, number of the segment, its units)
and probes, for every length that a threshold allows, only those stretches that
a segment can have moved to. Lines that meet are verified by a banded
bit-parallel edit distance: one field of bits for each number of errors, one bit
for each diagonal of the band.

Equal lines are one node, however often they occur. Lines that meet are held
against one line of their bucket first and against each other only where they
stay in different components (see ``components.bucket_components``).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reachgraph.llm.common import stored, sweep
from reachgraph.llm.components import bucket_components

#: Lines of as many words or more are compared by words, shorter ones of ``LEAST_CHARS`` characters or more by characters.
LEAST_WORDS, LEAST_CHARS = 8, 30
#: One edit of a word per so many words, at least 1 and at most ``MOST_EDITS``; so many edits of characters in lines of few words.
WORDS_PER_EDIT, MOST_EDITS, CHAR_EDITS = 20, 4, 2
#: Neighbouring words, or characters of lines of few words, that are one token where lines are looked up by tokens.
WORD_TOKEN, CHAR_TOKEN = 3, 5


def allowed(by_words: Column, n: Column) -> Column:
    """How many edits a line of ``n`` units may be apart from another that is not shorter."""
    words = F.least(F.lit(MOST_EDITS), F.greatest(F.lit(1), F.floor(n / WORDS_PER_EDIT).cast("int")))
    return F.when(by_words, words).otherwise(F.lit(CHAR_EDITS))


def probes(threshold: int) -> list[tuple[int, int, int, int]]:
    """(threshold, units longer than the indexed line, segment, shift) of each probe.

    A segment with i segments before it can have moved by as many units as
    there are edits left for those, and what lies behind it limits it likewise.
    """
    out = []
    for longer in range(threshold + 1):
        for i in range(threshold + 1):
            low = max(-i, longer - (threshold - i))
            high = min(i, longer + (threshold - i))
            out += [(threshold, longer, i, shift) for shift in range(low, high + 1)]
    return out


def _constant(ways: list[tuple[int, int, int, int]]) -> str:
    return "array(" + ", ".join(f"named_struct('edits', {t}, 'longer', {d}, 'i', {i}, 'shift', {s})" for t, d, i, s in ways) + ")"


def bucket_rows(nodes: DataFrame) -> DataFrame:
    """(key, node): every line as index entries and as probes; an entry and the probe that it answers have equal keys.

    ``nodes`` has node, by_words, n and units. The probes of a threshold are a
    constant that is exploded before keys are made from it, so that the compiled
    code stays small enough to be optimised. Near a length where the threshold
    changes, a line probes shorter ones under their threshold.
    """
    spark_ways = [_constant(probes(t)) for t in range(1, max(MOST_EDITS, CHAR_EDITS) + 1)]
    edits = allowed(F.col("by_words"), F.col("n"))
    own = F.element_at(F.expr(f"array({', '.join(spark_ways)})"), edits)
    every = F.expr(f"concat({', '.join(spark_ways)})")
    fits = lambda way: allowed(F.col("by_words"), F.col("n") - way["longer"]) == way["edits"]
    ways = F.when(edits == allowed(F.col("by_words"), F.col("n") - edits), own).otherwise(F.filter(every, fits))
    each = nodes.select("node", "by_words", "n", "units", F.explode(ways).alias("w"))
    length, parts = "(n - w.longer)", "(w.edits + 1)"
    larger = f"(w.i - {parts} + {length} % {parts})"  # the last segments are one unit longer, this many before this one
    first = f"w.i * ({length} div {parts}) + greatest(0, {larger}) + w.shift + 1"
    size = f"({length} div {parts}) + if({larger} >= 0, 1, 0)"
    return each.select(F.expr(f"xxhash64(by_words, {length}, w.i, slice(units, cast({first} as int), cast({size} as int)))").alias("key"), "node")


def within(a: Column, b: Column, edits: Column, most: int = max(MOST_EDITS, CHAR_EDITS)) -> Column:
    """Whether two arrays of units are at most ``edits`` (up to ``most``, 5 at most) insertions, deletions and replacements apart.

    The state is one number. Its field e has a bit for each diagonal d of the
    band, which says that the first j units of ``b`` can become the first
    j - most + d of ``a`` with e errors. A unit of ``b`` moves all fields at once:
    a match keeps a bit, a replacement or an insertion carries it to the next
    field, and so do deletions, as many as there are fields left.
    """
    width = 2 * most + 2  # the diagonals and one bit that stays empty
    low = sum(1 << (width * e) for e in range(most + 1))  # the first bit of every field
    mask = lambda first, since: F.lit(sum(((1 << (2 * most + 1)) - (1 << first)) << (width * e) for e in range(since, most + 1))).cast("long")

    def moved(state: Column, j: Column) -> Column:
        unit = F.get(b, j - 1)
        match = F.lit(0).cast("long")
        for d in range(2 * most + 1):
            match = match + F.when(F.get(a, j - 1 - most + d).eqNullSafe(unit), F.lit(low << d).cast("long")).otherwise(F.lit(0).cast("long"))
        next_field = F.shiftleft(state, width)
        return state.bitwiseAND(match).bitwiseOR(next_field.bitwiseAND(mask(0, 1))).bitwiseOR(F.shiftright(next_field, 1).bitwiseAND(mask(0, 1)))

    def closed(state: Column) -> Column:
        out = state
        for n in range(1, most + 1):
            out = out.bitwiseOR(F.shiftleft(state, n * (width + 1)).bitwiseAND(mask(n, n)))
        return out

    start = F.lit(sum((((1 << (e + 1)) - 1) << most) << (width * e) for e in range(most + 1))).cast("long")
    columns = F.when(F.size(b) > 0, F.sequence(F.lit(1), F.size(b))).otherwise(F.array().cast("array<int>"))
    # a transform over one value gives it a name, so that it is worked out once
    last = F.aggregate(columns, start, lambda state, j: F.element_at(F.transform(F.array(moved(state, j)), closed), 1))
    place = edits * width + F.greatest(F.lit(0), F.size(a) - F.size(b) + most)
    return (F.abs(F.size(a) - F.size(b)) <= edits) & (F.call_function("shiftright", last, place.cast("int")).bitwiseAND(F.lit(1).cast("long")) == 1)


def grams(units: Column, n: Column, by_words: Column) -> Column:
    """Hashes of the runs of neighbouring units, once each; an edit can change as many of them as a run is long."""
    width = F.when(by_words, F.lit(WORD_TOKEN)).otherwise(F.lit(CHAR_TOKEN))
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), n - width + 1)), lambda i: F.hash(F.slice(units, i, width))))


def token_rows(nodes: DataFrame) -> DataFrame:
    """(node, by_words, n, pos, token, m): the tokens of lines with their places, and how many places of all lines have each.

    Tokens are runs of neighbouring units, so that an exchanged word makes
    tokens that are rare even where the word is not.
    """
    width = F.when(F.col("by_words"), F.lit(WORD_TOKEN)).otherwise(F.lit(CHAR_TOKEN))
    tokens = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.col("n") - width + 1)), lambda i: F.array_join(F.slice("units", i, width), " "))
    rows = nodes.select("node", "by_words", "n", F.posexplode(tokens).alias("pos", "word"))
    rows = stored(rows.select("node", "by_words", "n", "pos", F.xxhash64("by_words", "word").alias("token")), "tokens")
    return stored(rows.join(rows.groupBy("token").agg(F.count(F.lit(1)).alias("m")), "token"), "tokens")


def first_tokens(rows: DataFrame) -> DataFrame:
    """Those of ``token_rows`` that come first in their line, from rare to frequent: until the allowed edits cannot have changed all before.

    An edit changes tokens of as many neighbouring places as a token is long.
    What edits leave of two lines within the threshold is equal on both sides
    and in the same order, so the rarest of it is among the first tokens of both.
    """
    order = Window.partitionBy("node").orderBy("m", "token", "pos")
    edits = allowed(F.col("by_words"), F.col("n"))
    width = F.when(F.col("by_words"), F.lit(WORD_TOKEN)).otherwise(F.lit(CHAR_TOKEN))
    some = rows.withColumn("place", F.row_number().over(order)).where(F.col("place") <= edits * width + 1)
    before = F.sort_array(F.collect_list("pos").over(order.rowsBetween(Window.unboundedPreceding, -1)))
    start = F.struct(F.lit(0).alias("past"), F.lit(0).alias("edits"))
    step = lambda a, pos: F.when(pos < a["past"], a).otherwise(F.struct((pos + width).alias("past"), (a["edits"] + 1).alias("edits")))
    needed = F.aggregate("before", start, step, lambda a: a["edits"])
    return some.withColumn("before", before).where(needed <= edits).drop("place", "before")


def possible_links(rows: DataFrame, open_: DataFrame) -> DataFrame:
    """(a, b): pairs of ``open_(node, label, outer)`` of different labels, one outer, among them all within the threshold.

    Lines within the threshold share one of their first tokens, and its places
    and what lies behind it are apart by no more than the edits allow.
    """
    first = first_tokens(rows.join(open_.select("node"), "node", "left_semi")).where("m > 1")
    first = stored(first.drop("m").join(open_, "node"), "first")
    # outer lines meet all others, those of the main component only outer ones
    sides = F.when(F.col("outer"), F.array(F.lit(False), F.lit(True))).otherwise(F.array(F.lit(False)))
    left = first.select("token", "by_words", F.explode(sides).alias("tame"), "node", "n", "pos", "label")
    right = first.select("token", "by_words", (~F.col("outer")).alias("tame"), *[F.col(c).alias(f"o_{c}") for c in ("node", "n", "pos", "label")])
    shift, longer = F.col("pos") - F.col("o_pos"), F.col("n") - F.col("o_n")
    close = F.abs(shift) + F.abs(longer - shift) <= allowed(F.col("by_words"), F.least("n", "o_n"))
    once = F.col("tame") | (F.col("node") > F.col("o_node"))
    return (
        left.join(right, ["token", "by_words", "tame"])
        .where((F.col("label") != F.col("o_label")) & close & once)
        .select(F.greatest("node", "o_node").alias("a"), F.least("node", "o_node").alias("b"))
        .distinct()
    )


def lines_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, line_no (from 0), line: every line of every text; null texts have none."""
    split = F.posexplode(F.split(F.col(text_col).cast("string"), "\n"))
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), split.alias("line_no", "line"))


def _words() -> Column:
    """The words of a line, which blanks separate."""
    return F.array_remove(F.split("line", " "), "")


def near_duplicate_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", least_chars: int = LEAST_CHARS, short_lines: bool = False) -> DataFrame:
    """doc_id, line_no, n_chars, first_doc, first_line, kept: one row per line of ``least_chars`` characters or more.

    With ``short_lines`` also one per shorter line that is not empty; these are
    classed by equality alone.

    Lines that both have ``LEAST_WORDS`` words or more are linked if their words
    are within ``allowed`` edits of the shorter one; lines that both have fewer
    if their characters are within ``CHAR_EDITS``. (first_doc, first_line) is
    the first occurrence, by id and line number, of any line that links lead to,
    and names the class. ``kept`` marks that occurrence. The number of blanks between
    words does not count. Null texts have no lines; null ids come after all
    others; repeated rows share their positions and so are kept or not together;
    a very long line is a line like any other. Other columns are not read; an
    empty table gives an empty result.
    """
    rows = lines_of(docs, id_col, text_col).where(F.char_length("line") >= (1 if short_lines else least_chars))
    place = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "line_no")
    rows = rows.select("doc_id", "line_no", "line", F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(1), "line").alias("h2"), F.char_length("line").alias("n_chars"), place.alias("place"))
    nodes = rows.groupBy("h1", "h2").agg(F.first("line").alias("line"), F.first("n_chars").alias("n_chars"), F.min("place").alias("place"), F.count(F.lit(1)).alias("rows"))
    # numbers are given once and written down, so that they stay; the units of a line are made from it again where they are needed, as they take more room
    nodes = nodes.withColumn("words", F.size(_words())).withColumn("node", F.monotonically_increasing_id())
    by_words = F.col("words") >= LEAST_WORDS
    n = F.when(F.col("n_chars") >= least_chars, F.when(by_words, F.col("words")).otherwise(F.col("n_chars")))
    nodes = stored(nodes.select("h1", "h2", "place", "rows", "node", by_words.alias("by_words"), n.alias("n"), F.when(F.col("n_chars") >= least_chars, F.col("line")).alias("line")), "lines")
    lines = nodes.where("n is not null").select("node", "by_words", "n", "line")
    units = F.when(F.col("by_words"), _words()).otherwise(F.split("line", "")).alias("units")

    texts: list[DataFrame] = []
    tokens: list[DataFrame] = []

    def verifier(members: DataFrame) -> Callable[[DataFrame], DataFrame]:
        wanted = lines.join(members.select("node").distinct(), "node", "left_semi").select("node", "by_words", "n", units)
        wanted = wanted.withColumn("grams", grams(F.col("units"), F.col("n"), F.col("by_words")))
        texts.append(stored(wanted, "texts"))

        def verify(pairs: DataFrame) -> DataFrame:
            facts, units_of = texts[0].select("node", "by_words", "n", "grams"), texts[0].select("node", "units")
            of = lambda df, side: df.select(*[F.col(c).alias(f"{side}_{c}") for c in df.columns])
            met = pairs.join(of(facts, "a"), F.col("a") == F.col("a_node")).join(of(facts, "b"), F.col("b") == F.col("b_node")).where("a_by_words = b_by_words")
            met = met.withColumn("edits", allowed(F.col("a_by_words"), F.least("a_n", "b_n"))).where(F.abs(F.col("a_n") - F.col("b_n")) <= F.col("edits"))
            width = F.when(F.col("a_by_words"), WORD_TOKEN).otherwise(CHAR_TOKEN)
            for one, other in (("a_grams", "b_grams"), ("b_grams", "a_grams")):
                met = met.where(F.size(F.array_except(one, other)) <= F.col("edits") * width)
            near = met.select("a", "b", "edits").join(of(units_of, "a"), F.col("a") == F.col("a_node")).join(of(units_of, "b"), F.col("b") == F.col("b_node"))
            return near.where(within(F.col("a_units"), F.col("b_units"), F.col("edits"))).select("a", "b")

        return verify

    def weigh(some: DataFrame) -> DataFrame:
        # the line whose tokens most others have is nearest to all of them
        tokens.append(token_rows(texts[0].join(some, "node", "left_semi")))
        return tokens[0].groupBy("node").agg(F.avg("m").alias("weight"))

    labels = bucket_components(bucket_rows(lines.select("node", "by_words", "n", units)), verifier, lambda open_: possible_links(tokens[0], open_), weigh)
    sweep(docs.sparkSession)
    # a line that occurs once and is linked with none is its own class; only the others travel
    own = nodes.select("node", "h1", "h2", "place", "rows").join(labels, "node", "left").where("label is not null or rows > 1")
    own = own.select("h1", "h2", F.coalesce("label", "node").alias("label"), "place")
    first = own.groupBy("label").agg(F.min("place").alias("first"))
    classes = stored(own.join(first, "label").select("h1", "h2", "first"), "classes")
    first = F.coalesce("first", "place")
    return (
        rows.select("doc_id", "line_no", "n_chars", "h1", "h2", "place")
        .join(classes, ["h1", "h2"], "left")
        .select(
            "doc_id",
            F.col("line_no").cast("long").alias("line_no"),
            F.col("n_chars").cast("long").alias("n_chars"),
            first["doc_id"].alias("first_doc"),
            first["line_no"].cast("long").alias("first_line"),
            (F.col("place") == first).alias("kept"),
        )
    )


def drop_duplicate_lines(docs: DataFrame, **options: object) -> DataFrame:
    """The documents without their repeated lines, with all columns; ``n_chars`` follows the text.

    Lines of under ``least_chars`` characters stay unless ``short_lines`` is set:
    brackets, headings and blanks are parts of many texts and copies of none.

    A document of which only blank lines would be left, though it had others, is
    dropped: all it said stands elsewhere. Documents that lose no line come
    back as they are.
    """
    id_col, text_col = str(options.get("id_col", "doc_id")), str(options.get("text_col", "text"))
    drop = (
        near_duplicate_lines(docs, **options)
        .where(~F.col("kept"))
        .groupBy(F.col("doc_id").alias("_id"))
        .agg(F.sort_array(F.collect_set("line_no")).alias("_drop"))
    )
    lines = F.split(F.col(text_col), "\n")
    left = F.array_join(F.filter(lines, lambda line, i: ~F.array_contains("_drop", i.cast("long"))), "\n")
    joined = docs.join(drop.hint("shuffle_hash"), docs[id_col].cast("long").eqNullSafe(drop["_id"]), "left")
    text = F.when(F.col("_drop").isNull(), F.col(text_col)).otherwise(left)
    kept = joined.withColumn("_text", text).where(F.col("_drop").isNull() | (F.trim("_text") != ""))
    columns = []
    for c in docs.columns:
        if c == text_col:
            columns.append(F.col("_text").alias(c))
        elif c == "n_chars":
            columns.append(F.when(F.col("_drop").isNull(), F.col(c)).otherwise(F.char_length("_text").cast(docs.schema[c].dataType)).alias(c))
        else:
            columns.append(F.col(c))
    return kept.select(*columns)
