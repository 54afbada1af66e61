import numpy as np
import pytest
from conftest import SMALL

from stationlink.operators import evaluate
from stationlink.operators.trees import TrainPart, cuts, grow
from stationlink.plans import experiments


def sparse(x, base):
    """index, value, first of a matrix; zeros from column ``base`` on take no room."""
    kept = [[j for j in range(x.shape[1]) if j < base or r[j]] for r in x]
    return np.array([j for k in kept for j in k]), np.array([r[j] for r, k in zip(x, kept) for j in k]), np.r_[0, np.cumsum([len(k) for k in kept])]


def some_rows(n=300):
    r = np.random.default_rng(3)
    x = np.c_[r.random((n, 2)) * 9, r.integers(-2, 3, (n, 4)) * (r.random((n, 4)) < 0.4)].astype(float)
    return x, ((x[:, 0] > 4) ^ (x[:, 3] > 0) | (r.random(n) < 0.1)).astype(int)


class OneOfEach:
    """Draws each row once, and features in order."""

    def poisson(self, lam, n):
        return np.ones(n, int)

    def random(self, shape):
        return np.tile(np.arange(shape[1], dtype=float), (shape[0], 1))


def test_first_split_is_the_best_of_all():
    x, y = some_rows()
    tree = grow(TrainPart.of(*sparse(x, 2), y, 2, 6, 1000), 6, 1, OneOfEach())
    mixed = lambda z: 2 * len(z) * z.mean() * (1 - z.mean()) if len(z) else 0
    every = {(j, t): mixed(y) - mixed(y[x[:, j] <= t]) - mixed(y[x[:, j] > t]) for j in range(6) for t in cuts(np.r_[x[:, j], 0.0] if j > 1 else x[:, j], 1000)}
    assert tree["gain"][0] * len(y) == pytest.approx(max(every.values())) and every[tree["feature"][0], tree["threshold"][0]] == pytest.approx(max(every.values()))


@pytest.mark.parametrize("cells", [4_000_000, 50])
def test_a_deep_tree_tells_all_its_rows_apart(monkeypatch, cells):
    monkeypatch.setattr("stationlink.operators.trees.CELLS", cells)
    x, y = some_rows()
    tree = grow(TrainPart.of(*sparse(x, 2), y, 2, 6, 1000), 6, 30, OneOfEach())
    at = np.zeros(len(y), int)
    for _ in range(31):
        f = tree["feature"][at]
        at = np.where(f < 0, at, np.where(x[np.arange(len(y)), f] <= tree["threshold"][at], tree["left"][at], tree["right"][at]))
    assert (tree["left"][at] < 0).all() and ((tree["ones"] > tree["zeros"])[at] == y).all()
    inner = tree["left"] >= 0
    assert all((tree[c][inner] == tree[c][tree["left"][inner]] + tree[c][tree["right"][inner]]).all() for c in ("zeros", "ones"))


def test_cuts_share_out_rows():
    assert list(cuts(np.array([3.0, 1, 1, 2, np.nan]), 256)) == [1.5, 2.5]
    x = np.random.default_rng(1).random(5000)
    code = np.searchsorted(cuts(x, 16), x)
    assert np.bincount(code).min() > 300 and len(np.unique(code)) == 16


def test_vectors_are_made_once_for_all_forests(spark, monkeypatch):
    from stationlink.operators import forest

    made, real = [], forest.vectors
    monkeypatch.setattr(forest, "vectors", lambda *a: made.append(a) or real(*a))
    settings = [("small", {"k": 5, "grids": 0, "trees": 3, "max_depth": 5}), ("large", {"k": 40, "grids": 2, "trees": 3, "max_depth": 5})]
    got = {(r.setting, r.repeat): r for r in experiments.forest_rows(spark, SMALL, settings, repeats=(0, 1)).collect()}
    assert len(made) == 1 and len(got) == 4
    rows = experiments.forest_pairs(spark, SMALL, repeats=(0, 1))
    for name, changed in settings:  # the same as from vectors of its own
        alone = forest.RandomForestMatcher(**changed).fit(rows.where("train1")).transform(rows.where("not train1"))
        own = evaluate.confusion(alone).first()
        assert (own.tp, own.fp, own.fn, own.tn) == tuple(got[name, 1][c] for c in ("tp", "fp", "fn", "tn"))


def test_trees_stay_out_of_the_drivers_java(spark, monkeypatch):
    """Trees are grown in tasks; the library's model is made from their table only when asked for."""
    from stationlink.operators import forest

    monkeypatch.setattr(forest.RandomForestMatcher, "_fit_by_library", None)
    rows = experiments.forest_pairs(spark, SMALL)
    f = forest.RandomForestMatcher(trees=3, k=20, max_depth=8).fit(rows.where("train0"))
    assert f._model is None and len(f.flat.roots) == 3 and f.model.getNumTrees == 3 and f.model.numFeatures == f.width


def test_a_large_train_part_is_fitted_by_the_library_on_all_rows(spark, monkeypatch):
    from stationlink.operators import forest

    monkeypatch.setattr(forest, "TASK_ENTRIES", 10)
    got = experiments.forest_rows(spark, SMALL, [("few", {"k": 20, "grids": 1, "trees": 5, "max_depth": 8}), ("more", {"k": 60, "trees": 5, "max_depth": 8})])
    assert all(r.f1 > 0.8 for r in got.collect())
