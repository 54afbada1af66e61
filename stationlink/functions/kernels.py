"""String measures without a built-in, for Arrow batches of label pairs."""

from __future__ import annotations

import re
from functools import lru_cache

import numpy as np

_SPLIT = re.compile(r"[^\w]+")


def jaro(a: str, b: str) -> float:
    """Jaro similarity; 1 for two empty labels."""
    if a == b:
        return 1.0
    n, m = len(a), len(b)
    if not n or not m:
        return 0.0
    reach = max(max(n, m) // 2 - 1, 0)
    taken = [False] * m
    mine = []
    for i, c in enumerate(a):
        for j in range(max(0, i - reach), min(m, i + reach + 1)):
            if not taken[j] and b[j] == c:
                taken[j] = True
                mine.append(c)
                break
    k = len(mine)
    if not k:
        return 0.0
    other = (c for c, t in zip(b, taken) if t)
    swapped = sum(x != y for x, y in zip(mine, other)) // 2
    return (k / n + k / m + (k - swapped) / k) / 3


def jaro_winkler(a: str, b: str, p: float = 0.1, max_prefix: int = 4, gate: float = 0.7) -> float:
    j = jaro(a, b)
    if j <= gate and gate > 0:
        return j
    prefix = 0
    for x, y in zip(a[:max_prefix], b[:max_prefix]):
        if x != y:
            break
        prefix += 1
    return j + prefix * p * (1 - j)


def edit_row(row: np.ndarray, text: str, label: np.ndarray) -> np.ndarray:
    """Edit-distance row over all prefixes of ``label`` after ``text`` is appended to what gave ``row``."""
    step = np.arange(len(row))
    for c in text:
        new = np.empty_like(row)
        new[0] = row[0] + 1
        new[1:] = np.minimum(row[1:] + 1, row[:-1] + (label != ord(c)))
        row = np.minimum.accumulate(new - step) + step  # insertions, left to right
    return row


def prefix_edit(a: str, b: str, norm: str = "whole") -> float:
    """Length less the smallest edit distance of one label to a prefix of the other, over the whole one's (or longer) length."""
    if not a or not b:
        return float(a == b)
    la, lb = (np.frombuffer(x.encode("utf-32-le"), np.uint32) for x in (a, b))
    of_a = edit_row(np.arange(len(b) + 1), a, lb).min()  # a whole, prefixes of b
    of_b = edit_row(np.arange(len(a) + 1), b, la).min()
    longer = max(len(a), len(b))
    n, m = (len(a), len(b)) if norm == "whole" else (longer, longer)
    return max((n - of_a) / n, (m - of_b) / m)


@lru_cache(maxsize=1 << 14)
def tokens(label: str) -> tuple[str, ...]:
    return tuple(dict.fromkeys(t for t in _SPLIT.split(label) if t))


def token_jaccard(a: str, b: str) -> float:
    x, y = set(tokens(a)), set(tokens(b))
    return len(x & y) / len(x | y) if x or y else float(a == b)


def best_orderings(own: tuple[str, ...], whole: str) -> float:
    """Best edit similarity of any ordering of any non-empty subset of tokens to a whole label.

    The row of a subset is the smallest, place by place, over its last token: appending is monotone, so the minimum may be
    taken before. Costs 2^m * m rows for m tokens, and equals trying all orderings.
    """
    label = np.frombuffer(whole.encode("utf-32-le"), np.uint32)
    start = np.arange(len(label) + 1)
    rows: dict[int, np.ndarray] = {}
    size: dict[int, int] = {}
    best = 0.0
    for subset in range(1, 1 << len(own)):
        row = None
        for k, token in enumerate(own):
            if subset >> k & 1:
                rest = subset ^ (1 << k)
                new = edit_row(rows[rest], " " + token, label) if rest else edit_row(start, token, label)
                row = new if row is None else np.minimum(row, new)
        last = subset.bit_length() - 1
        rest = subset ^ (1 << last)
        size[subset] = size[rest] + 1 + len(own[last]) if rest else len(own[last])
        rows[subset] = row
        longer = max(size[subset], len(label), 1)
        best = max(best, (longer - row[-1]) / longer)
    return float(best)


def best_token_subsequence(a: str, b: str, max_tokens: int | None = 6) -> float:
    """Best of both directions; token Jaccard if either label has more than ``max_tokens`` tokens or none."""
    x, y = tokens(a), tokens(b)
    if a == b:
        return 1.0
    if not x or not y or (max_tokens is not None and max(len(x), len(y)) > max_tokens):
        return token_jaccard(a, b)
    return max(best_orderings(x, b), best_orderings(y, a))


def _codes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(code points padded with 0, lengths)."""
    size = np.array([len(t) for t in texts])
    out = np.zeros((len(texts), max(int(size.max(initial=0)), 1)), np.uint32)
    for k, t in enumerate(texts):
        out[k, : len(t)] = np.frombuffer(t.encode("utf-32-le"), np.uint32)
    return out, size


def _columns(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(code points with one text a column, padded with 0; lengths); batches of many short texts are added up column-wise much faster."""
    codes, size = _codes(texts)
    codes = np.ascontiguousarray(codes.T)
    return codes.astype(np.uint16) if int(codes.max(initial=0)) < 1 << 16 else codes, size


def _row_type(*sizes: np.ndarray) -> type:
    """A type for edit distances, less their place, between texts of these lengths."""
    most = sum(int(s.max(initial=0)) + 1 for s in sizes)
    return np.int8 if most < 127 else np.int16 if most < 1 << 15 else np.int32


def _append(row: np.ndarray, same: np.ndarray) -> np.ndarray:
    """Edit-distance rows, less their place, once a character is appended that equals the labels' where ``same``.

    Without the place an insertion costs nothing, so what insertions give is a running minimum.
    """
    new = row + row.dtype.type(1)
    np.minimum(new[1:], row[:-1] - same, out=new[1:])
    for i in range(1, len(new)):
        np.minimum(new[i], new[i - 1], out=new[i])
    return new


def best_orderings_many(own: list[tuple[str, ...]], whole: list[str]) -> np.ndarray:
    """``best_orderings`` of many (tokens, label) with the same number of tokens, row by row over all of them at once."""
    label, length = _columns(whole)
    n, m = len(own), len(own[0])
    tokens = [_columns([x[k] for x in own]) for k in range(m)]
    kind = _row_type(length, *[size for _, size in tokens])
    blank = (label == ord(" ")).astype(kind)
    steps = [[((label == codes[j]).astype(kind), j < size) for j in range(len(codes))] for codes, size in tokens]
    start = np.zeros((len(label) + 1, n), kind)

    def append(row: np.ndarray, k: int) -> np.ndarray:
        for same, inside in steps[k]:
            new = _append(row, same)
            if not inside.all():
                np.copyto(new, row, where=~inside)
            row = new
        return row

    rows: dict[int, np.ndarray] = {}
    best, at = np.zeros(n), np.arange(n)
    for subset in range(1, 1 << m):
        row, total = None, np.full(n, -1)
        for k in range(m):
            if subset >> k & 1:
                total = total + 1 + tokens[k][1]
                rest = subset ^ (1 << k)
                new = append(rows[rest] if rest else start, k)
                row = new if row is None else np.minimum(row, new, out=row)
        longer = np.maximum(np.maximum(total, length), 1)
        best = np.maximum(best, (longer - (row[length, at] + length)) / longer)
        rows[subset] = _append(row, blank) if subset + 1 < 1 << m else row  # as other tokens follow after a space
    return best


def best_token_subsequences(a: list[str], b: list[str], max_tokens: int | None = 6, batch: int = 4096) -> np.ndarray:
    """``best_token_subsequence`` of many pairs."""
    out = np.zeros(len(a))
    work: dict[int, list[tuple[int, tuple[str, ...], str]]] = {}
    for k, (p, q) in enumerate(zip(a, b)):
        x, y = tokens(p), tokens(q)
        if p == q:
            out[k] = 1.0
        elif not x or not y or (max_tokens is not None and max(len(x), len(y)) > max_tokens):
            out[k] = token_jaccard(p, q)
        else:
            work.setdefault(len(x), []).append((k, x, q))
            work.setdefault(len(y), []).append((k, y, p))
    for jobs in work.values():
        jobs.sort(key=lambda job: (len(job[2]), *map(len, job[1])))  # alike lengths need little padding
        for lo in range(0, len(jobs), batch):
            part = jobs[lo : lo + batch]
            np.maximum.at(out, [k for k, _, _ in part], best_orderings_many([x for _, x, _ in part], [w for _, _, w in part]))
    return out


def prefix_edits(a: list[str], b: list[str], batch: int = 4096) -> np.ndarray:
    """``prefix_edit`` of many pairs, over the whole label's length."""
    out = np.zeros(len(a))
    order = sorted(range(len(a)), key=lambda k: (len(a[k]), len(b[k])))  # alike lengths need little padding
    for lo in range(0, len(a), batch):
        part = order[lo : lo + batch]
        x, y = _columns([a[k] for k in part]), _columns([b[k] for k in part])
        n, m = x[1], y[1]
        got = np.maximum((n - _least_rows(x, y)) / np.maximum(n, 1), (m - _least_rows(y, x)) / np.maximum(m, 1))
        out[part] = np.where((n == 0) | (m == 0), ((n == 0) & (m == 0)).astype(float), got)
    return out


def _least_rows(text: tuple[np.ndarray, np.ndarray], label: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Least edit distance of each whole text to a prefix of its label, row by row over all of them at once."""
    (codes, size), (own, length) = text, label
    kind = _row_type(size, length)
    row = np.zeros((len(own) + 1, len(size)), kind)
    for j in range(len(codes)):
        new, inside = _append(row, (own == codes[j]).astype(kind)), j < size
        if not inside.all():
            np.copyto(new, row, where=~inside)
        row = new
    at = np.arange(len(own) + 1)[:, None]
    return np.where(at <= length, row + at, 1 << 30).min(axis=0)


def jaros(a: list[str], b: list[str], winkler: bool = False, batch: int = 2048) -> np.ndarray:
    """``jaro`` or ``jaro_winkler`` of many pairs."""
    out = np.zeros(len(a))
    for lo in range(0, len(a), batch):
        (x, n), (y, m) = _codes(a[lo : lo + batch]), _codes(b[lo : lo + batch])
        rows, place = np.arange(len(n)), np.arange(y.shape[1])
        reach = np.maximum(np.maximum(n, m) // 2 - 1, 0)[:, None]
        taken, mine = np.zeros(y.shape, bool), np.zeros(x.shape, bool)
        for i in range(x.shape[1]):
            free = (y == x[:, i, None]) & ~taken & (np.abs(place - i) <= reach) & (place < m[:, None]) & (i < n)[:, None]
            first = free.argmax(axis=1)
            hit = free[rows, first]
            taken[rows[hit], first[hit]] = mine[hit, i] = True
        k = mine.sum(axis=1)
        width = min(x.shape[1], y.shape[1])
        left, right = (np.take_along_axis(c, np.argsort(~f, axis=1, kind="stable"), axis=1)[:, :width] for c, f in ((x, mine), (y, taken)))
        swapped = ((left != right) & (np.arange(width) < k[:, None])).sum(axis=1) // 2
        full = np.maximum(k, 1)
        got = np.where(k > 0, (k / np.maximum(n, 1) + k / np.maximum(m, 1) + (k - swapped) / full) / 3, 0.0)
        same = np.array([p == q for p, q in zip(a[lo : lo + batch], b[lo : lo + batch])], bool)
        got[same] = 1.0
        if winkler:
            width = min(4, width)
            alike = (x[:, :width] == y[:, :width]) & (np.arange(width) < np.minimum(n, m)[:, None])
            got = np.where(got > 0.7, got + np.minimum.accumulate(alike, axis=1).sum(axis=1) * 0.1 * (1 - got), got)
        out[lo : lo + batch] = got
    return out
