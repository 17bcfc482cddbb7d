"""Metrics: an Arrow decoder, a numpy kernel and, where there is one, a native column expression each."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


#: Distances that ``Metric.within`` holds at a time where it has no prefilter.
MOST_CELLS = 1 << 20
#: Components of the pairs that are measured at a time, few enough to stay in cache.
MOST_COMPONENTS = 1 << 17


def slack(bound):
    """A bound that rounding of a prune test cannot undercut; the final test is exact."""
    return bound * (1 + 1e-9) + 1e-12


def matrix(col: pa.Array, dtype=float) -> np.ndarray:
    """A list column as an (n, d) matrix; all rows must have one length."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if not len(col):
        return np.empty((0, 0), dtype)
    flat = col.flatten().to_numpy(zero_copy_only=False)
    if len(flat) % len(col):
        raise ValueError("vectors differ in length")
    return flat.astype(dtype).reshape(len(col), -1)


def objects(values) -> np.ndarray:
    out = np.empty(len(values), object)
    out[:] = values
    return out


@dataclass
class Metric:
    """``to(block, x)`` are the distances from one point to a block. ``evaluations`` counts them. ``prefilter(a, b, eps)`` gives
    (i, j, open): pairs with none at most eps apart missing, and which of them may lie farther. Without ``measured``, ``within`` finds and
    counts the same pairs, but gives nan for the distances of those that the prefilter is sure of."""

    name: str
    decode: Callable[[pa.Array], np.ndarray]
    to: Callable[[np.ndarray, object], np.ndarray]
    native: Callable[[Column, Column], Column] | None = None
    is_metric: bool = True
    integer: bool = False
    prefilter: Callable[[np.ndarray, np.ndarray, float], tuple[np.ndarray, np.ndarray, np.ndarray]] | None = None
    pairs: Callable[[np.ndarray, np.ndarray, float], tuple[np.ndarray, np.ndarray, np.ndarray]] | None = None
    measured: bool = True
    evaluations: int = field(default=0, compare=False)

    def row(self, block: np.ndarray, x) -> np.ndarray:
        self.evaluations += len(block)
        return self.to(block, x)

    def table(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """All distances, by the shorter side."""
        if len(a) <= len(b):
            return np.array([self.row(b, x) for x in a]).reshape(len(a), len(b))
        return np.array([self.row(a, x) for x in b]).reshape(len(b), len(a)).T

    def near(self, a: np.ndarray, b: np.ndarray, eps: float) -> np.ndarray:
        """Whether points of a (rows) and of b (columns) lie at most eps apart: by squared distances from a matrix product for
        metrics with a prefilter, what rounding leaves open measured again."""
        if self.prefilter is None or not len(a) or not len(b):
            return self.table(a, b) <= eps
        self.evaluations += len(a) * len(b)
        na, nb = (a * a).sum(1), (b * b).sum(1)
        left, right = np.column_stack([a, na, np.ones(len(a))]), np.ascontiguousarray(np.column_stack([-2 * b, np.ones(len(b)), nb]).T)
        room = 1e-9 * (na.max() + nb.max() + eps * eps)
        out = np.empty((len(a), len(b)), bool)
        # tiles that stay in cache
        for k in range(0, len(a), 128):
            for c in range(0, len(b), 2048):
                ok, squared = out[k : k + 128, c : c + 2048], left[k : k + 128] @ right[:, c : c + 2048]
                np.less_equal(squared, eps * eps + room, out=ok)
                sure = squared < eps * eps - room
                if np.count_nonzero(sure) != np.count_nonzero(ok):
                    i, j = np.nonzero(ok != sure)
                    ok[i, j] = self.apart(a, b, i + k, j + c) <= eps
        return out

    def apart(self, a: np.ndarray, b: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Distances of the pairs (a[i], b[j])."""
        if self.prefilter is None:
            return self.table(a, b)[i, j]
        step = max(1, MOST_COMPONENTS // max(1, a.shape[1]))
        return np.concatenate([np.empty(0), *(self.to(b[j[k : k + step]], a[i[k : k + step]]) for k in range(0, len(i), step))])

    def within(self, a: np.ndarray, b: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(i, j, distance) of the pairs at most eps apart."""
        if not len(a) or not len(b):
            return np.empty(0, int), np.empty(0, int), np.empty(0)
        if self.prefilter is not None and len(a) * len(b) > 256:
            i, j, unsure = self.prefilter(a, b, eps)
            self.evaluations += len(a) * len(b)
            if self.measured:
                d = self.apart(a, b, i, j)
            else:
                d = np.full(len(i), np.nan)
                d[unsure] = self.apart(a, b, i[unsure], j[unsure])
            far = np.flatnonzero(d > eps)
            return (np.delete(i, far), np.delete(j, far), np.delete(d, far)) if len(far) else (i, j, d)
        if self.pairs is not None:
            self.evaluations += len(a) * len(b)
            return self.pairs(a, b, eps)
        found, step = [], max(1, MOST_CELLS // len(b))
        for k in range(0, len(a), step):
            d = self.table(a[k : k + step], b)
            i, j = np.nonzero(d <= eps)
            found.append((i + k, j, d[i, j]))
        return tuple(np.concatenate(c) for c in zip(*found))


def _l2_prefilter(a: np.ndarray, b: np.ndarray, eps: float, cells: int = 1 << 18, wide: int = 2048) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Squared distances by one matrix product of the points lengthened by their squared norms, in tiles that stay in cache, with
    room for rounding. Numbers are of single precision where its room (each product of d + 2 terms, of sizes that add up to twice the
    squared norms at most) is small beside eps squared."""
    na, nb = (a * a).sum(1), (b * b).sum(1)
    square, top = eps * eps, na.max() + nb.max()
    kind, room = np.float64, 1e-9 * (top + square)
    single = 2.0**-21 * ((a.shape[1] + 8) * top + square)
    if 1e-30 < square and top < 1e30 and single <= 1e-3 * square:
        kind, room = np.float32, single
    left = np.column_stack([a, na, np.ones(len(a))]).astype(kind)
    right = np.column_stack([-2 * b, np.ones(len(b)), nb]).T.astype(kind, "C")
    tall = max(1, cells // min(wide, len(b)))
    found = []
    for k in range(0, len(a), tall):
        for c in range(0, len(b), wide):
            squared = left[k : k + tall] @ right[:, c : c + wide]
            at = np.flatnonzero(squared <= square + room)
            i = at // squared.shape[1]
            found.append((i + k, at - i * squared.shape[1] + c, squared.ravel()[at] >= square - room))
    return tuple(np.concatenate(f) for f in zip(*found))


def l2_to(block: np.ndarray, x: np.ndarray) -> np.ndarray:
    return np.sqrt(((block - x) ** 2).sum(1))


def hamming_to(block: np.ndarray, x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(block ^ x).sum(1).astype(float)


def unit(col: pa.Array) -> np.ndarray:
    x = matrix(col)
    n = np.sqrt((x * x).sum(1, keepdims=True))
    return np.divide(x, n, out=np.zeros_like(x), where=n > 0)


def jaccard_to(block: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Over sorted sets; two empty sets are at distance 0."""
    sizes = np.fromiter(map(len, block), np.int64, len(block))
    if not len(x) or not sizes.any():
        return np.where(sizes + len(x) > 0, 1.0, 0.0)
    flat = np.concatenate([y for y in block if len(y)])
    hit = x[np.minimum(np.searchsorted(x, flat), len(x) - 1)] == flat
    ends = np.cumsum(sizes)
    total = np.concatenate(([0], np.cumsum(hit)))
    both = total[ends] - total[ends - sizes]
    return 1 - both / (sizes + len(x) - both)


#: Letters that a machine word holds a pattern of, and classes of letters that are counted for a bound.
WORD, CLASSES = 64, 32


def _letters(strings: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(code points, a row a string and zeros behind it; lengths)."""
    sizes = np.fromiter(map(len, strings), np.int64, len(strings))
    width = max(1, int(sizes.max(initial=0)))
    return np.array(list(strings), f"U{width}").view(np.uint32).reshape(len(strings), -1), sizes


def _edit_words(bits: np.ndarray, i: np.ndarray, m: np.ndarray, codes: np.ndarray, j: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Edit distances of the pairs (i, j) from bit vectors of a table's column each, a letter of all texts at a time: ``bits[i, code]``
    are the places of a letter in pattern i of ``m`` <= WORD letters, ``codes[j]`` the ``n`` letters of text j."""
    order = np.argsort(-n[j], kind="stable")
    i, j = i[order], j[order]
    left = n[j]
    score = m[i].copy()
    top = np.where(score > 0, score - 1, 0).astype(np.uint64)
    one = np.uint64(1)
    up, down = np.full(len(i), ~np.uint64(0)), np.zeros(len(i), np.uint64)
    for c in range(int(left[0]) if len(left) else 0):
        k = int(np.searchsorted(-left, -c, "left"))  # texts that go on
        up, down = up[:k], down[:k]
        same = bits[i[:k], codes[j[:k], c]]
        across = (((same & up) + up) ^ up) | same
        along = same | down
        more, less = down | ~(across | up), up & across
        score[:k] += ((more >> top[:k]) & one).astype(np.int64) - ((less >> top[:k]) & one).astype(np.int64)
        more = (more << one) | one
        up, down = (less << one) | ~(along | more), more & along
    score = np.where(m[i] > 0, score, left)
    out = np.empty(len(i))
    out[order] = score
    return out


def edit_pairs(a: np.ndarray, b: np.ndarray, eps: float | None = None, pairs: int = 1 << 14) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(i, j, distance) of all pairs of strings, with ``eps`` of those at most that far apart. Pairs whose letters alone tell more than eps are not measured."""
    short = np.fromiter(map(len, a), np.int64, len(a)) <= WORD
    found = []
    for x in np.flatnonzero(~short):
        d = _edit_rows(b, a[x])
        at = np.arange(len(b)) if eps is None else np.flatnonzero(d <= eps)
        found.append((np.full(len(at), x), at, d[at]))
    own = np.flatnonzero(short)
    if len(own) and len(b):
        pattern, m = _letters(a[own])
        letters = np.unique(pattern)
        place = np.minimum(np.searchsorted(letters, pattern), len(letters) - 1)
        row, col = np.nonzero(np.arange(pattern.shape[1]) < m[:, None])
        count = lambda signs, n: np.minimum(np.bincount((np.arange(len(n))[:, None] * CLASSES + signs % CLASSES)[np.arange(signs.shape[1]) < n[:, None]], minlength=len(n) * CLASSES), 127).astype(np.int8).reshape(len(n), -1)
        ca = count(pattern, m)
        wide = max(1, (1 << 22) // max(1, max(map(len, b))))
        tall = max(1, (1 << 21) // (len(letters) + 1))
        for hi in range(0, len(b), wide):
            text, n = _letters(b[hi : hi + wide])
            k = np.minimum(np.searchsorted(letters, text), len(letters) - 1)
            codes = np.where(letters[k] == text, k, len(letters))
            cb = np.ascontiguousarray(count(text, n).T) if eps is not None else None
            for lo in range(0, len(own), tall):
                some = (row >= lo) & (row < lo + tall)
                bits = np.zeros((min(tall, len(own) - lo), len(letters) + 1), np.uint64)
                np.bitwise_or.at(bits, (row[some] - lo, place[row[some], col[some]]), np.uint64(1) << col[some].astype(np.uint64))
                mine, size = ca[lo : lo + tall], m[lo : lo + tall]
                if eps is None:
                    i, j = np.divmod(np.arange(len(mine) * len(n)), len(n))
                else:
                    # half of what letters differ by and of what lengths do bounds the distance from below
                    near = lambda letters, length, others, lengths: np.flatnonzero(np.abs(others - letters[:, None]).sum(0, dtype=np.int32) + np.abs(lengths - length) <= 2 * eps)
                    if len(mine) <= len(n):
                        each = [near(mine[x], size[x], cb, n) for x in range(len(mine))]
                        i, j = np.repeat(np.arange(len(mine)), list(map(len, each))), np.concatenate(each)
                    else:
                        across = np.ascontiguousarray(mine.T)
                        each = [near(cb[:, y], n[y], across, size) for y in range(len(n))]
                        i, j = np.concatenate(each), np.repeat(np.arange(len(n)), list(map(len, each)))
                for at in range(0, len(i), pairs):
                    x, y = i[at : at + pairs], j[at : at + pairs]
                    d = _edit_words(bits, x, size, codes, y, n)
                    ok = slice(None) if eps is None else d <= eps
                    found.append((own[x[ok] + lo], y[ok] + hi, d[ok]))
    return tuple(np.concatenate(c) for c in zip(*found)) if found else (np.empty(0, int), np.empty(0, int), np.empty(0))


def edit_to(block: np.ndarray, x: str, pairs: int = 1 << 14) -> np.ndarray:
    """Edit distances in code points, of so many pairs at a time."""
    _, j, d = edit_pairs(objects([x]), block, pairs=pairs)
    out = np.empty(len(block))
    out[j] = d
    return out


def _edit_rows(block: np.ndarray, x: str, cells: int = 1 << 20) -> np.ndarray:
    """Edit distances, a row of the table for all strings at once."""
    out = np.empty(len(block))
    sizes = np.fromiter(map(len, block), np.int64, len(block))
    width = int(sizes.max(initial=0))
    step = max(1, cells // (width + 1))
    at = np.arange(width + 1, dtype=np.int32)
    for lo in range(0, len(block), step):
        part = block[lo : lo + step]
        signs = np.array(list(part), f"U{max(width, 1)}").view(np.uint32).reshape(len(part), -1)[:, :width]
        row = np.tile(at, (len(part), 1))
        for i, c in enumerate(map(ord, x), 1):
            new = np.empty_like(row)
            new[:, 0] = i
            np.minimum(row[:, :-1] + (signs != c), row[:, 1:] + 1, out=new[:, 1:])
            # an insertion adds one for each place to the right: a running minimum without that slope
            new -= at
            np.minimum.accumulate(new, axis=1, out=new)
            new += at
            row = new
        out[lo : lo + step] = row[np.arange(len(part)), sizes[lo : lo + step]]
    return out


def _fold(a: Column, b: Column, each, start=0.0) -> Column:
    return F.aggregate(F.zip_with(a, b, each), F.lit(start), lambda s, x: s + x)


def _as_double(c: Column) -> Column:
    return c.cast("array<double>")


def metric(name: str, bin_width: float = 1.0) -> Metric:
    """l2, l1, linf, hamming (packed longs), edit, angular, chord, cosine (no metric), w1 (CDF arrays), jaccard (sorted sets)."""
    pair = lambda f: lambda a, b: f(_as_double(a), _as_double(b))
    if name == "l2":
        return Metric(name, matrix, l2_to, pair(lambda a, b: F.sqrt(_fold(a, b, lambda x, y: (x - y) * (x - y)))), prefilter=_l2_prefilter)
    if name == "l1":
        return Metric(name, matrix, lambda y, x: np.abs(y - x).sum(1), pair(lambda a, b: _fold(a, b, lambda x, y: F.abs(x - y))))
    if name == "linf":
        return Metric(name, matrix, lambda y, x: np.abs(y - x).max(1), pair(lambda a, b: F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x - y)))))
    if name == "w1":
        return Metric(name, matrix, lambda y, x: np.abs(y - x).sum(1) * bin_width, pair(lambda a, b: _fold(a, b, lambda x, y: F.abs(x - y)) * bin_width))
    if name == "hamming":
        return Metric(name, lambda c: matrix(c, np.int64).view(np.uint64), hamming_to, lambda a, b: _fold(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y)), 0).cast("double"), integer=True)
    if name == "angular":
        cosine = lambda a, b: _fold(a, b, lambda x, y: x * y) / F.sqrt(_fold(a, a, lambda x, y: x * y) * _fold(b, b, lambda x, y: x * y))
        return Metric(name, unit, lambda y, x: np.arccos(np.clip((y * x).sum(-1), -1, 1)), pair(lambda a, b: F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), cosine(a, b))))))
    if name == "chord":
        return Metric(name, unit, l2_to, prefilter=_l2_prefilter)
    if name == "cosine":
        return Metric(name, unit, lambda y, x: 1 - (y * x).sum(-1), is_metric=False)
    if name == "edit":
        return Metric(name, lambda c: objects(c.to_pylist()), edit_to, lambda a, b: F.levenshtein(a, b).cast("double"), integer=True, pairs=edit_pairs)
    if name == "jaccard":
        return Metric(name, lambda c: objects([np.unique(np.array(v)) for v in c.to_pylist()]), jaccard_to, lambda a, b: 1 - F.size(F.array_intersect(a, b)) / F.size(F.array_union(a, b)))
    raise ValueError(f"no metric {name!r}")


def custom(name: str, to: Callable, decode: Callable | None = None, native: Callable | None = None, is_metric: bool = True) -> Metric:
    """A user's metric from the distances of one point to a block."""
    return Metric(name, decode or (lambda c: objects(c.to_pylist())), to, native, is_metric)


def resolve(m: str | Metric) -> Metric:
    return metric(m) if isinstance(m, str) else m


def native_l2(a: Column, b: Column, dim: int) -> Column:
    """Unrolled for few dimensions, so that the expression stays in generated code."""
    total = F.lit(0.0)
    for i in range(dim):
        total = total + (a[i] - b[i]) * (a[i] - b[i])
    return F.sqrt(total)
