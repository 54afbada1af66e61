"""Trees of a forest grown level by level on a train part that one task holds, all open nodes of a level at once."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np

#: Histogram cells looked at together; wider levels are taken in parts.
CELLS = 4_000_000


class TrainPart(NamedTuple):
    """Rows in codes: value <= cuts[c] if and only if code <= c. Features from ``base`` on are sparse and share their cuts."""

    base: int
    width: int
    dense: np.ndarray
    dense_cuts: list[np.ndarray]
    row: np.ndarray
    feature: np.ndarray
    code: np.ndarray
    cuts: np.ndarray
    truth: np.ndarray

    @classmethod
    def of(cls, index: np.ndarray, value: np.ndarray, first: np.ndarray, truth: np.ndarray, base: int, width: int, bins: int) -> TrainPart:
        """From sparse rows index[first[k]:first[k + 1]]; an index below 0 is no feature of this forest."""
        row = np.repeat(np.arange(len(truth), dtype=np.int32), np.diff(first))
        head, tail = (index >= 0) & (index < base), index >= base
        x = np.zeros((len(truth), base))
        x[row[head], index[head]] = value[head]
        dense_cuts = [cuts(x[:, j], bins) for j in range(base)]
        dense = np.stack([np.searchsorted(c, x[:, j]) for j, c in enumerate(dense_cuts)], axis=1).astype(np.int16)
        own = cuts(np.r_[value[tail], 0.0], bins)
        return cls(base, width, dense, dense_cuts, row[tail], index[tail].astype(np.int32), np.searchsorted(own, value[tail]).astype(np.int16), own, truth.astype(bool))


def cuts(x: np.ndarray, bins: int) -> np.ndarray:
    """Middles between neighbouring values: all, or those after equal shares of the rows if there are more than ``bins`` values."""
    u, n = np.unique(x[~np.isnan(x)], return_counts=True)
    at = np.arange(len(u) - 1)
    if len(u) > bins:
        at = np.unique(np.searchsorted(np.cumsum(n), n.sum() * np.arange(1, bins) / bins))
        at = at[at < len(u) - 1]
    return (u[at] + u[at + 1]) / 2


def _best(weight: np.ndarray, hits: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For histograms (node, feature, code): the place of the best feature, its cut and the gain in Gini impurity, 0 if nothing is gained."""
    w, h = weight.cumsum(2), hits.cumsum(2)
    all_w, all_h = w[:, :1, -1:], h[:, :1, -1:]
    w, h = w[:, :, :-1], h[:, :, :-1]
    rest_w, rest_h = all_w - w, all_h - h
    with np.errstate(divide="ignore", invalid="ignore"):
        mixed = h * (w - h) / w + rest_h * (rest_w - rest_h) / rest_w
    gain = np.where((w > 0) & (rest_w > 0), 2 * (all_h * (all_w - all_h) / all_w - mixed) / all_w, 0.0).reshape(len(w), -1)
    if not gain.shape[1]:
        return np.zeros(len(w), int), np.zeros(len(w), int), np.zeros(len(w))
    at = gain.argmax(1)
    most = gain[np.arange(len(w)), at]
    return at // w.shape[2], at % w.shape[2], np.where(most > 1e-12, most, 0.0)


def _splits(part: TrainPart, node, dense, row, feature, code, w, h, nodes: int, tries: int, rng) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(feature, cut, gain) of each of ``nodes`` open nodes over its own ``tries`` features drawn without replacement, and the entries of drawn features."""
    best_f, best_c, best_g = np.zeros(nodes, int), np.zeros(nodes, int), np.zeros(nodes)
    zero, codes = int(np.searchsorted(part.cuts, 0.0)), len(part.cuts) + 1
    step = max(1, CELLS // max(part.width, tries * codes, *(len(c) + 1 for c in part.dense_cuts)))
    of_entry, looked = node.take(row), []
    for lo in range(0, nodes, step):
        m = min(step, nodes - lo)
        drawn = rng.random((m, part.width)).argpartition(tries - 1, axis=1)[:, :tries] if tries < part.width else np.tile(np.arange(part.width), (m, 1))
        slot = np.full((m, part.width), -1, np.int16)
        np.put_along_axis(slot, drawn, np.arange(tries, dtype=np.int16)[None, :], 1)
        r = np.arange(len(node)) if m == nodes else np.flatnonzero((node >= lo) & (node < lo + m))
        e = slice(None) if m == nodes else np.flatnonzero((of_entry >= lo) & (of_entry < lo + m))
        f, c, g = best_f[lo : lo + m], best_c[lo : lo + m], best_g[lo : lo + m]
        if codes > 1:
            place = slot.ravel().take((of_entry[e] - lo) * part.width + feature[e])
            hit = np.flatnonzero(place >= 0)
            place = place.take(hit)
            hit = hit if m == nodes else e.take(hit)
            looked.append(hit)
            key = ((of_entry.take(hit) - lo) * tries + place) * codes + code.take(hit)
            own = row.take(hit)
            hw, hh = (np.bincount(key, x[own], m * tries * codes).astype(float).reshape(m, tries, codes) for x in (w, h))  # counts of nothing are whole numbers
            for a, x in ((hw, w), (hh, h)):  # what has no entry is a zero
                a[:, :, zero] += np.bincount(node[r] - lo, x[r], m)[:, None] - a.sum(2)
            k, c[:], g[:] = _best(hw, hh)
            f[:] = drawn[np.arange(m), k]
        for j, own_cuts in enumerate(part.dense_cuts):
            has = np.flatnonzero(slot[:, j] >= 0)
            if not len(has) or not len(own_cuts):
                continue
            short = np.full(m, -1)
            short[has] = np.arange(len(has))
            n = short[node[r] - lo]
            own = r[n >= 0]
            key = n[n >= 0] * (len(own_cuts) + 1) + dense[own, j]
            hw, hh = (np.bincount(key, x[own], len(has) * (len(own_cuts) + 1)).reshape(len(has), 1, -1) for x in (w, h))
            _, cut, gain = _best(hw, hh)
            better = gain > g[has]
            f[has[better]], c[has[better]], g[has[better]] = j, cut[better], gain[better]
    return best_f, best_c, best_g, np.concatenate(looked) if looked else np.zeros(0, int)


def grow(part: TrainPart, tries: int, depth: int, rng: np.random.Generator) -> dict[str, np.ndarray]:
    """One tree on a bag of rows (Poisson weights). Children come after their parent; two leaves that predict the same are one."""
    bag = rng.poisson(1.0, len(part.truth))
    if not bag.any():
        bag[:] = 1
    kept = np.flatnonzero(bag)
    new = np.cumsum(bag > 0) - 1
    inside = np.flatnonzero((bag > 0).take(part.row))
    row, feature, code = new.take(part.row.take(inside)), part.feature.take(inside), part.code.take(inside)
    dense, w = part.dense[kept], bag[kept].astype(float)
    h = w * part.truth[kept]
    node, zero = np.zeros(len(kept), int), int(np.searchsorted(part.cuts, 0.0))
    total, ones = [np.array([w.sum()])], [np.array([h.sum()])]
    found: list[tuple[np.ndarray, ...]] = []  # of each level: its nodes, feature, threshold, gain, left child
    opened, count = np.arange(1)[(ones[0] > 0) & (ones[0] < total[0])], 1
    if not len(opened):
        node = node[:0]
    for _ in range(depth):
        if not len(node):
            break
        f, c, g, looked = _splits(part, node, dense, row, feature, code, w, h, len(opened), tries, rng)
        split = g > 0
        right = np.where(f[node] >= part.base, zero > c[node], False)
        own = np.flatnonzero(f[node] < part.base)
        right[own] = dense[own, f[node[own]]] > c[node[own]]
        own = row.take(looked)
        at = node.take(own)
        hit = feature.take(looked) == f[at]
        right[own[hit]] = code.take(looked[hit]) > c[at[hit]]
        child = np.cumsum(split) * 2 - 2  # number of the left child in the next level
        side = child[node] + right
        going = split[node]
        m = 2 * int(split.sum())
        tw, th = np.bincount(side[going], w[going], m), np.bincount(side[going], h[going], m)
        limit = np.array([part.dense_cuts[i][j] if i < part.base else part.cuts[j] for i, j in zip(f[split], c[split])])
        found.append((opened[split], f[split], limit, g[split], count + child[split]))
        total.append(tw)
        ones.append(th)
        stays = (th > 0) & (th < tw)
        short = np.where(stays, np.cumsum(stays) - 1, -1)
        opened, count = count + np.flatnonzero(stays), count + m
        goes_on = np.zeros(len(node), bool)
        goes_on[going] = stays[side[going]]
        new = np.cumsum(goes_on) - 1
        inside = np.flatnonzero(goes_on.take(row))
        node = short[side[goes_on]]
        row, feature, code = new.take(row.take(inside)), feature.take(inside), code.take(inside)
        dense, w, h = dense[goes_on], w[goes_on], h[goes_on]
    tw, th = np.concatenate(total), np.concatenate(ones)
    says = th > tw - th
    out_f, left, limit, gain = np.full(count, -1), np.full(count, -1), np.full(count, np.nan), np.full(count, -1.0)
    alive = np.ones(count, bool)
    for nodes, f, t, g, first in reversed(found):
        leaves = (left[first] < 0) & (left[first + 1] < 0) & (says[first] == says[first + 1])
        alive[first[leaves]] = alive[first[leaves] + 1] = False
        nodes, f, t, g, first = (x[~leaves] for x in (nodes, f, t, g, first))
        out_f[nodes], limit[nodes], gain[nodes], left[nodes] = f, t, g, first
    new = np.cumsum(alive) - 1
    inner = left[alive] >= 0
    first = np.where(inner, new[left[alive]], -1)
    return {"feature": out_f[alive], "threshold": limit[alive], "left": first, "right": np.where(inner, first + 1, -1), "gain": gain[alive], "zeros": (tw - th)[alive], "ones": th[alive]}
