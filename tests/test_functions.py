import itertools
import random

import pytest
from pyspark.sql import functions as F

from stationlink.functions import geo, kernels, naive, similarity, text, voting


def one(spark, *columns):
    return spark.range(1).select(*columns).first()


def test_rescale_worked_example_and_ends(spark):
    got = one(spark, *[voting.rescale(F.lit(s), t) for s, t in ((0.9, 0.8), (0.0, 0.0), (1.0, 1.0), (0.8, 0.8), (0.4, 0.8), (0.0, 1.0))])
    assert list(got) == pytest.approx([0.75, 0.0, 0.5, 0.5, 0.25, 0.0])


def test_decay_is_half_at_its_distance(spark):
    got = one(spark, naive.decay(F.lit(0.0), 50), naive.decay(F.lit(50.0), 50), naive.decay(F.lit(100.0), 50))
    assert list(got) == pytest.approx([1, 0.5, 0.25])
    with pytest.raises(ValueError):
        naive.decay(F.lit(1.0), 0)


def test_hard_votes(spark):
    got = one(spark, voting.hard(F.lit(1), F.lit(0)), voting.hard(F.lit(1), F.lit(1)), voting.hard(F.lit(1), F.lit(0), F.lit(1)), voting.hard(F.lit(1), F.lit(0), tie=1))
    assert list(got) == [0, 1, 1, 1]


def test_trigrams_are_padded_and_as_many_as_characters(spark):
    got = one(spark, text.trigrams(F.lit("abcdef")), text.trigrams(F.lit("")), text.trigrams(F.lit("ü")))
    assert got[0] == [" ab", "abc", "bcd", "cde", "def", "ef "] and got[1] == [] and got[2] == [" ü "]


def test_normalization_is_idempotent_and_keeps_tokens_whole(spark):
    labels = ["Freiburg, Hbf.", "Bahnhofstraße", "Mozartstr. 5", "St Georg-Platz", "A+B & C", " x  y ", "", "Ost \"Tor\"", "Hauptstrasse"]
    df = spark.createDataFrame([(x,) for x in labels], "l string").withColumn("n", text.normalize(F.col("l")))
    rows = df.withColumn("again", text.normalize(F.col("n"))).collect()
    got = {r.l: r.n for r in rows}
    assert all(r.n == r.again for r in rows)
    assert got["Freiburg, Hbf."] == "freiburg hauptbahnhof" and got["Bahnhofstraße"] == "bahnhof strasse"
    assert got["A+B & C"] == "a und b und c" and got[" x  y "] == "x y"


def test_tokens_split_outside_letters_of_any_language(spark):
    assert one(spark, text.tokens(F.lit("Telegrafstraße (Süd), Gleis-2")))[0] == ["Telegrafstraße", "Süd", "Gleis", "2"]


def test_grid_cells_of_a_known_place(spark):
    cells = one(spark, geo.grid_cells(F.lit(48.0), F.lit(7.84), 2))[0]
    assert [(c.x, c.y) for c in cells] == [(133, 196), (133, 195)]
    edge = one(spark, geo.grid_cells(F.lit(-90.0), F.lit(-180.0), 2))[0]
    assert [(c.x, c.y) for c in edge] == [(0, 0), (255, 0)]


def _words(r, most):
    return " ".join("".join(r.choice("abc") for _ in range(r.randint(1, 4))) for _ in range(r.randint(0, most)))


def test_best_ordering_equals_trying_all_orderings():
    r = random.Random(5)

    def tried(own, whole):
        best = 0.0
        for k in range(1, len(own) + 1):
            for p in itertools.permutations(own, k):
                s = " ".join(p)
                row = list(range(len(whole) + 1))
                for i, c in enumerate(s, 1):
                    row = _next(row, i, c, whole)
                best = max(best, 1 - row[-1] / max(len(s), len(whole)))
        return best

    def _next(row, i, c, whole):
        new = [i]
        for j, d in enumerate(whole, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != d)))
        return new

    pairs = [(_words(r, 4), _words(r, 4)) for _ in range(150)]
    many = kernels.best_token_subsequences([a for a, _ in pairs], [b for _, b in pairs])
    for (a, b), got in zip(pairs, many):
        x, y = kernels.tokens(a), kernels.tokens(b)
        want = 1.0 if a == b else kernels.token_jaccard(a, b) if not x or not y else max(tried(x, b), tried(y, a))
        assert got == pytest.approx(want) and kernels.best_token_subsequence(a, b) == pytest.approx(want)


def test_jaro_known_values():
    assert kernels.jaro("MARTHA", "MARHTA") == pytest.approx(0.944444, abs=1e-6)
    assert kernels.jaro_winkler("MARTHA", "MARHTA") == pytest.approx(0.961111, abs=1e-6)
    assert kernels.jaro("", "") == 1 and kernels.jaro("a", "") == 0
    assert kernels.jaro_winkler("abxyzq", "abcdef") == pytest.approx(0.5556, abs=1e-4)
    assert kernels.jaro_winkler("abcdefgh", "abcdefxy") == pytest.approx(0.9, abs=1e-4)


def test_measures_are_symmetric_in_range_and_agree_with_kernels(spark):
    r = random.Random(9)
    labels = [_words(r, 3) for _ in range(60)] + ["", "ü", "Süd"]
    pairs = [(r.choice(labels), r.choice(labels)) for _ in range(200)] + [(x, x) for x in labels]
    df = spark.createDataFrame(pairs, "a string, b string")
    cols = {m: f for m, f in similarity.MEASURES.items()}
    rows = df.select("a", "b", *[f(F.col("a"), F.col("b")).alias(m) for m, f in cols.items()], *[f(F.col("b"), F.col("a")).alias(f"r{m}") for m, f in cols.items()]).collect()
    for row in rows:
        for m in cols:
            assert 0 <= row[m] <= 1 and row[m] == pytest.approx(row[f"r{m}"]), (m, row)
            if row.a == row.b:
                assert row[m] == 1
        assert row.PED == pytest.approx(kernels.prefix_edit(row.a, row.b)) and row.PED >= row.ED - 1e-9 and row.JW >= row.J - 1e-9
        assert row.JAC == pytest.approx(kernels.token_jaccard(row.a, row.b))


def test_batched_measures_equal_the_single_ones():
    import random

    r = random.Random(9)
    make = lambda: "".join(r.choice("abcé ") for _ in range(r.choice([0, 1, 2, 5, 9, 17])))
    pairs = [(make(), make()) for _ in range(3000)] + [("abc", "abc"), ("", ""), ("martha", "marhta"), ("dixon", "dicksonx")]
    a, b = [list(x) for x in zip(*pairs)]
    for many, one in ((kernels.prefix_edits, kernels.prefix_edit), (kernels.jaros, kernels.jaro), (lambda p, q: kernels.jaros(p, q, winkler=True), kernels.jaro_winkler)):
        assert max(abs(x - one(p, q)) for x, p, q in zip(many(a, b), a, b)) < 1e-12


def test_scores_at_a_threshold_are_not_above_it():
    """3 of 20 characters are kept: 1 - 17 / 20 is above 0.15, (20 - 17) / 20 is not."""
    a, b = "abc" + "d" * 17, "abc"
    assert kernels.prefix_edits(["abc" + "d" * 17], ["abc" + "e" * 17])[0] == kernels.prefix_edit("abc" + "d" * 17, "abc" + "e" * 17) == 3 / 20
    assert kernels.best_orderings_many([(a,)], [b])[0] == kernels.best_orderings((a,), b) == 3 / 20
