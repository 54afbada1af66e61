import hashlib
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from stationlink.llm import decontaminate, lm_score, quality, toxicity
from stationlink.llm.queries import ORACLES, QUERIES

ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(text):
    return ALNUM.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


@pytest.mark.parametrize("name", ["op2_winnowing_decontamination", "op4_cross_entropy_difference", "op6_flow_mixing", "op7_prefix_target_chat", "op9_crf_extraction"])
def test_query_equals_its_sql(name, same):
    same(name, QUERIES[name], ORACLES[name])


def test_contamination_equals_brute_force(spark):
    r = random.Random(2)
    vocabulary = ["a", "b", "c", "é", "x1"]
    make = lambda lo, hi: " ".join(r.choice(vocabulary) for _ in range(r.randint(lo, hi)))
    items = [(k, make(1, 25)) for k in range(12)] + [(90, None), (91, "..."), (92, "Solo-Word twice"), (92, "a second text of item ninety two is here now")]
    docs = [(k, make(0, 80)) for k in range(60)] + [(100, None), (101, ""), (102, "x SOLO word, twice"), (103, "b " * 4000), (104, items[3][1].upper()), (104, items[3][1])]
    bench = spark.createDataFrame(items, "item_id long, text string").withColumn("spans", F.lit(1))
    df = spark.createDataFrame(docs, "doc_id long, text string").withColumn("items", F.lit("clash"))
    want = []
    for k, t in docs:
        w, hit, ids = words(t), set(), set()
        for i, text in items:
            x = words(text)
            n = min(10, len(x))
            for s in range(len(x) - n + 1 if n else 0):
                for p in range(len(w) - n + 1):
                    if w[p : p + n] == x[s : s + n]:
                        hit |= set(range(p, p + n))
                        ids.add(str(i))
        want.append((k, len(w), len(hit), sorted(ids)))
    for size in (1 << 20, 300):  # one pass, and several
        got = [(x.doc_id, x.n_words, sum(s.end - s.start for s in x.spans), list(x["items"])) for x in decontaminate.find_contamination(df, bench, pass_bytes=size).collect()]
        assert sorted(got) == sorted(want)
    df = df.withColumns({c: F.lit(c) for c in ("__f", "n_words", "spans")})
    clean = decontaminate.drop_contaminated(df, bench)
    assert clean.columns == df.columns and clean.count() == sum(not w[3] for w in want)
    assert decontaminate.find_contamination(df, bench.limit(0)).where("size(items) > 0").count() == 0


def test_maximal_segments_equal_the_recursive_definition():
    def by_definition(score, lo):
        best = None
        for i in range(len(score)):
            for j in range(i + 1, len(score) + 1):
                s = score[i:j].sum()
                if s > 1e-12 and (best is None or s > best[2] + 1e-9 or (abs(s - best[2]) <= 1e-9 and j - i < best[1] - best[0])):
                    best = (i, j, s)
        if best is None:
            return []
        i, j, s = best
        return by_definition(score[:i], lo) + [(lo + i, lo + j, s)] + by_definition(score[j:], lo + j)

    r = np.random.default_rng(3)
    for _ in range(60):
        score = r.normal(-0.2, 1, 25)
        got, want = toxicity.maximal_segments(score), by_definition(score, 0)
        assert [(a, b) for a, b, _ in got] == [(a, b) for a, b, _ in want]
        assert toxicity.best_segments(score, np.array([0, 25]))[0] == pytest.approx(max([x[2] for x in want], default=0))


def test_segments_of_a_very_long_text_are_found_in_linear_time():
    import time

    r = np.random.default_rng(5)
    score = r.normal(-0.2, 1, 1_000_000)
    began = time.time()
    got = toxicity.maximal_segments(score)
    assert time.time() - began < 60
    total = np.r_[0.0, np.cumsum(score)]
    assert all(a < b for a, b, _ in got) and all(x[1] <= y[0] for x, y in zip(got, got[1:]))
    assert max(x[2] for x in got) == pytest.approx(toxicity.best_segments(score, np.array([0, len(score)]))[0])
    assert all(s == pytest.approx(total[b] - total[a]) for a, b, s in got[:1000])


def graded(n=400):
    r = random.Random(6)
    rows, labels = [], []
    for k in range(n):
        w = ["".join(r.choice("abcdefgh") for _ in range(r.randint(2, 5))) for _ in range(r.randint(5, 60))]
        toxic, junk = k % 5 == 0, k % 7 == 0
        if toxic:
            for _ in range(3):
                w.insert(r.randrange(len(w)), r.choice(["idiot", "scum"]))
        rows.append((k, "%%% ".join(w) if junk else " ".join(w)))
        labels.append((k, int(not junk), int(toxic)))
    return rows, labels


def test_toxicity_on_held_out_rows_and_edge_cases(spark):
    rows, labels = graded()
    docs = spark.createDataFrame([*rows, (1000, None), (1001, ""), (None, "you idiot scum idiot")], "doc_id long, text string").withColumn("score", F.lit("clash"))
    lab = spark.createDataFrame([*labels, (3, 1, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.score(docs, toxicity.fit(docs, lab)).collect()}
    from zlib import crc32

    held = [k for k, _, _ in labels if crc32(str(k).encode()) % 5 == 0]
    assert sum((got[k].score >= 0.5) == bool(labels[k][2]) for k in held) / len(held) > 0.95
    assert got[None].score > 0.5 and len(got[None].passages) >= 1 and 0 <= got[1000].score < 0.5 and got[1001].passages == []


def test_toxicity_of_empty_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    lab = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert toxicity.score(none, toxicity.fit(none, lab)).count() == 0


def test_quality_grades_and_edge_cases(spark):
    rows, labels = graded()
    docs = spark.createDataFrame([*rows, (1000, None), (1001, "")], "doc_id long, text string").withColumn("tail", F.lit(1))
    lab = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    model = quality.fit(docs, lab)
    assert list(model.thresholds) == sorted(model.thresholds)
    got = {r.doc_id: r for r in quality.score(docs, model).collect()}
    assert sum(got[k].accepted == bool(q) for k, q, _ in labels) / len(labels) > 0.97
    assert all(0 <= r.expected_grade <= 2 for r in got.values())
    clash = docs.withColumns({c: F.lit(c) for c in ("__s", "accepted", "expected_grade")})
    assert quality.accepted(clash, model).columns == clash.columns and quality.accepted(clash, model).count() == sum(r.accepted for r in got.values())
    assert quality.accepted(docs, quality.fit(docs, lab.limit(0))).count() == docs.count()


def test_lm_scores_prefer_target_words(spark):
    rows = [(k, "alpha beta " * 5 if k % 2 else "gamma delta " * 5) for k in range(20)] + [(50, None), (51, "  ")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("target", F.lit("clash"))
    ids = spark.createDataFrame([(k,) for k in range(1, 20, 2)] + [(None,)], "doc_id long")
    model = lm_score.fit(lm_score.marked(docs, ids))
    got = {r.doc_id: r.difference for r in lm_score.score(docs, model).collect()}
    assert got[1] < 0 < got[2] and got[50] is None and got[51] is None
    wide = lm_score.fit(lm_score.marked(docs, ids, broadcast_ids=0))
    assert np.allclose(wide[1], model[1]) and np.allclose(wide[2], model[2])
    assert lm_score.score(docs, lm_score.fit(lm_score.marked(docs.limit(0), ids))).count() == 22


def test_query_digests_use_sorted_ids(spark):
    got = QUERIES["op2_winnowing_decontamination"](spark, "/root/testdata/sf0.001").where("n_items = 0").first()
    assert got.items_sha256 == hashlib.sha256(b"").hexdigest() and not got.contaminated


def test_lm_scores_of_many_buckets_equal_the_counts(spark, monkeypatch):
    r = random.Random(8)
    rows = [(k % 50, " ".join(f"w{int(r.paretovariate(0.5)) % 5000}" for _ in range(r.randint(0, 40))), k % 3 == 0) for k in range(300)] + [(None, None, False), (None, "w1 w2", True)]
    df = spark.createDataFrame(rows, "doc_id long, text string, target boolean")
    seqs = [(t or "").split() for _, t, _ in rows]
    from collections import Counter

    number = len({w for s in seqs for w in s}) + 1
    pair, context, word = ([Counter(), Counter()] for _ in range(3))
    for s, (_, _, flag) in zip(seqs, rows):
        for before, w in zip([None, *s], s):
            for m in (0, 1) if flag else (0,):
                pair[m][before, w] += 1
                context[m][before] += 1
                word[m][w] += 1

    def mean(s, m):
        loss = [-np.log2((0.6 * pair[m][b, w] / context[m][b] if context[m][b] else 0) + 0.35 * word[m][w] / sum(word[m].values()) + 0.05 / number) for b, w in zip([None, *s], s)]
        return round(float(np.mean(loss)), 6)

    want = sorted(((k, len(s), *([mean(s, 1), mean(s, 0)] if s else [None, None])) for (k, _, _), s in zip(rows, seqs)), key=repr)
    monkeypatch.setattr(lm_score, "BUCKET_BYTES", 1000)
    monkeypatch.setattr(lm_score, "VOCABULARY", 20)
    got = [(x.doc_id, x.n_words, *[None if v is None else round(v, 6) for v in (x.target_loss, x.background_loss)]) for x in lm_score.score_all(df).collect()]
    assert sorted(got, key=repr) == want
    assert lm_score.score_all(df.limit(0)).count() == 0
