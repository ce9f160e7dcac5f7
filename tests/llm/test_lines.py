"""Near-duplicate lines against brute force, edge cases at table level, and the bit-parallel distance."""

import random

import pytest
from pyspark.sql import functions as F

from reachgraph.llm.line_dedup import CHAR_EDITS, LEAST_WORDS, MOST_EDITS, WORDS_PER_EDIT, bucket_rows, drop_duplicate_lines, near_duplicate_lines, possible_links, token_rows, within

DOCS = "doc_id long, text string, lang string, source string, n_chars long, node long, units string, key string"


def documents(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), 7, "x", "y") for i, t in rows], DOCS)


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def linked(a, b):
    if a == b:
        return True
    if min(len(a), len(b)) < 30:
        return False
    u, v = a.split(), b.split()
    if min(len(u), len(v)) >= LEAST_WORDS:
        return distance(u, v) <= min(MOST_EDITS, max(1, min(len(u), len(v)) // WORDS_PER_EDIT))
    return max(len(u), len(v)) < LEAST_WORDS and distance(a, b) <= CHAR_EDITS


def edited(rng, units, fresh):
    out = list(units)
    for _ in range(rng.randint(0, 6)):
        at = rng.randrange(len(out) + 1)
        kind = rng.randrange(3)
        out[at : at + (kind != 0)] = [fresh()] if kind != 1 else []
    return out


def brute(rows):
    lines = [(i is None, i or 0, k, line) for i, t in rows if t is not None for k, line in enumerate(t.split("\n")) if line]
    lines.sort()
    label = list(range(len(lines)))
    for x in range(len(lines)):
        for y in range(x):
            if label[x] != label[y] and linked(lines[x][3], lines[y][3]):
                old, new = max(label[x], label[y]), min(label[x], label[y])
                label = [new if v == old else v for v in label]
    return [(None if none else i, k, None if lines[m][0] else lines[m][1], lines[m][2]) for (none, i, k, _), m in zip(lines, label, strict=True)]


def test_lines_against_brute_force(spark):
    rng = random.Random(11)
    vocabulary = [f"w{i}" for i in range(30)]
    fresh = lambda: rng.choice(vocabulary) + rng.choice("abc")
    rows = []
    for base in range(9):
        words = rng.choices(vocabulary, k=(9, 15, 24, 39, 41, 60, 79, 85, 120)[base])
        rows += [(base * 100 + k, " ".join(edited(rng, words, fresh))) for k in range(12)]
    for base in range(4):
        text = "".join(rng.choices("abcdefg", k=(33, 40, 58, 90)[base]))
        rows += [(2000 + base * 100 + k, "".join(edited(rng, text, lambda: rng.choice("abcdefg")))) for k in range(12)]
    rows += [(None, rows[0][1]), (5000, None), (5001, ""), (5002, "short\n\nshort\nShort"), (5003, rows[3][1] + "\n" + rows[3][1]), (5003, rows[3][1] + "\n" + rows[3][1])]
    rng.shuffle(rows)
    got = near_duplicate_lines(documents(spark, rows), short_lines=True).collect()
    expected = brute(rows)
    assert sorted(map(repr, ((r.doc_id, r.line_no, r.first_doc, r.first_line) for r in got))) == sorted(map(repr, expected))
    assert all(r.kept == ((r.doc_id, r.line_no) == (r.first_doc, r.first_line)) for r in got)
    # several classes, and classes of several lines
    assert 20 < len({(r.first_doc, r.first_line) for r in got}) < len(got) - 20


def test_lines_of_empty_and_odd_tables(spark):
    assert near_duplicate_lines(documents(spark, []), short_lines=True).count() == 0
    assert drop_duplicate_lines(documents(spark, [])).count() == 0
    long = " ".join(f"w{i}" for i in range(60_000))
    rows = [(1, long), (2, long + " tail"), (3, None), (None, "same words of a line that is there twice\nsame words of a line that is there twice"), (3, ""), (3, "")]
    df = documents(spark, rows)
    got = sorted((r.doc_id or 9, r.line_no, r.kept) for r in near_duplicate_lines(df).collect())
    assert got == [(1, 0, True), (2, 0, False), (9, 0, True), (9, 1, False)]
    out = drop_duplicate_lines(df)
    assert out.columns == df.columns
    assert sorted((r.doc_id or 9, (r.text or "")[:4]) for r in out.collect()) == [(1, "w0 w"), (3, ""), (3, ""), (3, ""), (9, "same")]


@pytest.mark.parametrize("most", [1, 2, 4])
def test_bit_parallel_distance(spark, most):
    rng = random.Random(most)
    pairs = []
    for _ in range(400):
        a = rng.choices("ab", k=rng.randint(0, 9))
        b = edited(rng, a, lambda: rng.choice("abc"))[: rng.randint(0, 9)] if a and rng.random() < 0.8 else rng.choices("ab", k=rng.randint(0, 9))
        pairs.append((a, b, rng.randint(0, most)))
    df = spark.createDataFrame(pairs, "a array<string>, b array<string>, edits int")
    for r in df.withColumn("near", within(F.col("a"), F.col("b"), F.col("edits"), most)).collect():
        assert r.near == (distance(r.a, r.b) <= r.edits), r


def test_lines_within_the_threshold_share_a_key(spark):
    rng = random.Random(3)
    lines, by_id = [], {}
    for base in range(60):
        units = [str(x) for x in rng.choices(range(50), k=rng.choice((8, 19, 20, 21, 39, 40, 42, 61, 80, 83)))]
        for _ in range(3):
            by_id[len(lines)] = edited(rng, units, lambda: str(rng.randrange(99)))
            lines.append((len(lines), True, len(by_id[len(lines)]), by_id[len(lines)]))
    rows = bucket_rows(spark.createDataFrame(lines, "node long, by_words boolean, n int, units array<string>")).collect()
    keys = {}
    for r in rows:
        keys.setdefault(r.node, set()).add(r.key)
    close = 0
    for x in by_id:
        for y in range(x):
            a, b = by_id[x], by_id[y]
            if distance(a, b) <= min(MOST_EDITS, max(1, min(len(a), len(b)) // WORDS_PER_EDIT)) and min(len(a), len(b)) >= 8:
                close += 1
                assert keys[x] & keys[y], (a, b)
    assert close > 20


def test_lines_that_differ_in_distant_places_are_not_proposed(spark):
    # one edit is allowed; the first word and the last one differ, which changes few tokens but takes two edits
    words = [f"w{i}" for i in range(20)]
    lines = [[f"a{k % 4}", *words, f"b{k // 4}"] for k in range(16)]
    rows = [(k, True, len(units), units) for k, units in enumerate(lines)]
    tokens = token_rows(spark.createDataFrame(rows, "node long, by_words boolean, n int, units array<string>"))
    open_ = spark.createDataFrame([(k, k, k > 0) for k in range(16)], "node long, label long, outer boolean")
    got = {(r.a, r.b) for r in possible_links(tokens, open_).collect()}
    near = {(x, y) for x in range(16) for y in range(x) if distance(lines[x], lines[y]) == 1}
    assert near <= got and len(got) < 16 * 15 // 2


def test_first_tokens_propose_all_links(spark):
    rng = random.Random(5)
    vocabulary = [f"w{i}" for i in range(12)]
    rows = []
    for n in (9, 21, 38, 41, 61, 82):
        words = rng.choices(vocabulary, k=n)
        for _ in range(14):
            units = edited(rng, words, lambda: rng.choice(vocabulary))
            rows.append((len(rows), True, len(units), units))
    rows = [r for r in rows if r[2] >= LEAST_WORDS]
    tokens = token_rows(spark.createDataFrame(rows, "node long, by_words boolean, n int, units array<string>"))
    open_ = spark.createDataFrame([(r[0], r[0], True) for r in rows], "node long, label long, outer boolean")
    got = {(r.a, r.b) for r in possible_links(tokens, open_).collect()}
    near = {(x[0], y[0]) for x in rows for y in rows if x[0] > y[0] and distance(x[3], y[3]) <= min(MOST_EDITS, max(1, min(x[2], y[2]) // WORDS_PER_EDIT))}
    assert len(near) > 40 and near <= got
