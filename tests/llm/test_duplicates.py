import random
import re

from pyspark.sql import functions as F

from stationlink.llm import near_dedup

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def shingles(text):
    w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set())


def brute(rows):
    sets = {k: shingles(t) for k, t in rows}
    parent = {k: k for k in sets}

    def top(k):
        while parent[k] != k:
            k = parent[k]
        return k

    keys = sorted(sets)
    for i, a in enumerate(keys):
        for b in keys[i + 1 :]:
            if sets[a] and sets[b]:
                common = len(sets[a] & sets[b])
                if 100 * common >= 75 * (len(sets[a]) + len(sets[b]) - common):
                    p, q = top(a), top(b)
                    parent[max(p, q)] = min(p, q)
    return {k: (len(sets[k]), top(k), top(k) == k) for k in keys}


def corpus():
    r = random.Random(4)
    vocabulary = [f"w{k}" for k in range(400)]
    base = [r.choice(vocabulary) for _ in range(120)]
    rows = []
    for k in range(120):  # a loose group: copies with more and more edits
        copy = list(base)
        for _ in range(k % 12):
            at = r.randrange(len(copy))
            copy[at : at + r.randint(0, 2)] = [r.choice(vocabulary)] * r.randint(0, 2)
        rows.append((k, " ".join(copy)))
    rows += [(200 + k, " ".join(r.choice(vocabulary) for _ in range(r.randint(1, 60)))) for k in range(60)]
    rows += [(300, None), (301, ""), (302, " \t\n"), (303, "one two"), (304, "ONE\x0btwo "), (305, "one two three four five"), (306, "one two three four five six"), (307, "a " * 3000)]
    rows += [(400 + k, rows[5][1]) for k in range(30)]
    return rows


def test_groups_equal_brute_force(spark):
    rows = corpus()
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("node", F.lit("x")).withColumn("n", F.lit(1))
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in near_dedup.near_duplicates(df).collect()}
    assert got == brute(rows)
    kept = near_dedup.drop_near_duplicates(df)
    assert kept.columns == df.columns and {r.doc_id for r in kept.collect()} == {k for k, v in brute(rows).items() if v[2]}


def test_empty_table_null_ids_and_repeated_rows(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert near_dedup.near_duplicates(none).count() == 0
    df = spark.createDataFrame([(None, "a b c d e f"), (5, "a b c d e f"), (5, "a b c d e f"), (6, "x y")], "doc_id long, text string")
    got = sorted(((r.doc_id, r.component_id, r.kept) for r in near_dedup.near_duplicates(df).collect()), key=repr)
    assert got == sorted([(None, 5, False), (5, 5, True), (5, 5, True), (6, 6, True)], key=repr)


def test_drop_keeps_different_texts_of_null_and_repeated_ids(spark):
    a, b, c, d = ("one two three four five six seven", "red green blue black white grey pink", "a lone text", "quite another text")
    rows = [(None, c), (None, d), (None, d), (None, a), (3, a), (5, a), (5, b), (5, b), (7, None), (7, ""), (None, None), (8, a.upper()), (9, b)]
    df = spark.createDataFrame([(*x, "tag") for x in rows], "doc_id long, text string, tag string")
    kept = near_dedup.drop_near_duplicates(df)
    got = sorted(((r.doc_id, r.text) for r in kept.collect()), key=repr)
    assert kept.columns == df.columns
    assert got == sorted([(None, c), (None, d), (3, a), (5, b), (7, None), (7, ""), (None, None)], key=repr)


def test_registers_keep_zeros_and_mantissa():
    import numpy as np

    x = np.array([1 << 63, (1 << 62) + (1 << 61), 1 << 40, 0, ~np.uint64(0)], np.uint64)
    got = near_dedup.compress(x)
    assert [int(g) >> near_dedup.MANTISSA for g in got] == [0, 1, 23, 53, 0]
    assert int(got[1]) & 1023 == 512 and int(got[4]) & 1023 == 1023


def test_estimates_are_near_the_truth():
    import numpy as np

    r = np.random.default_rng(1)
    pool = r.integers(0, 1 << 62, 3000).astype(np.uint64)
    a, b = np.unique(pool[:2000]), np.unique(pool[1000:])
    first = np.array([0, len(a), len(a) + len(b)])
    s = near_dedup.signatures(np.concatenate([a, b]), first)
    j = near_dedup.estimate(s[:1], s[1:], np.array([len(a)]), np.array([len(b)]))[0]
    assert abs(j - 1 / 3) < 0.15
