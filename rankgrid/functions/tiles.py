"""Tiles in full or low-rank form and their arithmetic.

A low-rank tile is X Wᵀ with X (m x r) and W (n x r). Every operation stays in low-rank form where the storage rule
allows, and the result is put through the rule again.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

FULL, LOW = "F", "L"
#: A full tile of which only the entries are stored; kernels get it as an array.
SPARSE = "S"


@dataclass
class Tile:
    """x is m x n in full form, m x rank in low-rank form; w is n x rank, None in full form."""

    x: np.ndarray
    w: np.ndarray | None = None

    @property
    def shape(self) -> tuple[int, int]:
        return self.x.shape if self.w is None else (self.x.shape[0], self.w.shape[0])

    @property
    def rank(self) -> int:
        return min(self.x.shape) if self.w is None else self.x.shape[1]

    @property
    def kind(self) -> str:
        return FULL if self.w is None else LOW

    @property
    def stored(self) -> int:
        return self.x.size + (0 if self.w is None else self.w.size)

    def dense(self) -> np.ndarray:
        return self.x if self.w is None else self.x @ self.w.T

    def norm(self) -> float:
        if self.w is None:
            return float(np.sqrt((self.x * self.x).sum()))
        # QR of one factor keeps the digits that the product of the two Gram matrices would lose
        return float(np.linalg.norm(np.linalg.qr(self.x, mode="r") @ self.w.T)) if self.rank else 0.0

    @property
    def T(self) -> Tile:
        return Tile(self.x.T) if self.w is None else Tile(self.w, self.x)

    def scaled(self, c: float) -> Tile:
        return Tile(self.x * c, self.w)


def pivoted_qr(a: np.ndarray, eps: float, most: int | None = None) -> tuple[np.ndarray, np.ndarray] | None:
    """X (orthonormal columns) and W with ‖a − X Wᵀ‖_F ≤ eps and the least rank that column pivoting reaches.

    The largest remaining column comes first. Columns are not updated as the work goes on: the next one is made orthogonal
    to X when its turn comes, until that takes no more than half of it, so that a step reads the matrix once and writes
    nothing of its size. Remaining norms are carried along and worked out anew once cancellation has eaten half of their
    digits. A last comparison with the matrix guards the bound. None if the rank passes most: the work ends there.
    """
    m, n = a.shape
    a = np.ascontiguousarray(a, dtype=np.float64)
    k, full = 0, min(m, n)
    limit = full if most is None else min(full, most)
    xt, wt = np.empty((limit, m)), np.empty((limit, n))
    left = (a * a).sum(axis=0)
    own, first, used, within = left.copy(), left.copy(), np.zeros(n, bool), False
    while k < full:
        if max(left.sum(), 0.0) <= 4 * eps * eps + 1e-30 and np.linalg.norm(a - xt[:k].T @ wt[:k]) <= eps:
            within = True
            break
        if most is not None and k >= most:
            return None
        p = int(np.where(used, -np.inf, left).argmax())
        v = a[:, p] - wt[:k, p] @ xt[:k]
        size = np.linalg.norm(v)
        for _ in range(4):
            v -= (xt[:k] @ v) @ xt[:k]
            before, size = size, np.linalg.norm(v)
            if 2 * size > before:
                break
        if size == 0.0:
            break
        xt[k] = v / size
        wt[k] = xt[k] @ a
        k += 1
        used[p] = True
        left -= wt[k - 1] ** 2
        left[used] = 0.0
        # an entry of W is as exact as its column of the matrix is long, whatever is left of that; what is left of a column
        # that is rounding alone has no digits to work out
        coarse = np.where(first > 1e-27 * own, 1e-14 * np.sqrt(first * own), 0.0)
        lost = np.flatnonzero((left <= np.maximum(1e-8 * first, coarse)) & ~used)
        if len(lost):
            left[lost] = ((a[:, lost] - xt[:k].T @ wt[:k, lost]) ** 2).sum(axis=0)
            first[lost] = np.maximum(left[lost], 1e-300)
    q, w = np.ascontiguousarray(xt[:k].T), np.ascontiguousarray(wt[:k].T)
    if k < full and not within and np.linalg.norm(a - q @ w.T) > eps * (1 + 1e-9) + 1e-14 * np.linalg.norm(a):
        u, s, vt = np.linalg.svd(a, full_matrices=False)
        k = int(np.searchsorted(-np.sqrt(np.cumsum(s[::-1] ** 2))[::-1], -eps))
        if most is not None and k > most:
            return None
        return u[:, :k], vt[:k].T * s[:k]
    return q, w


def keeps_low(rank: int, m: int, n: int) -> bool:
    """The storage rule: low-rank form up to half of the full rank."""
    return 2 * rank <= min(m, n)


def compress(a: np.ndarray, eps: float) -> Tile:
    """The tile of a dense block in the form that the storage rule asks for; rank 0 for a block within eps of zero."""
    found = pivoted_qr(a, eps, min(a.shape) // 2)
    return Tile(*found) if found else Tile(np.ascontiguousarray(a, dtype=np.float64))


def compress_all(a: np.ndarray, eps: tuple[float, ...]) -> list[tuple[Tile, float]]:
    """compress(a, e) for each threshold, and its measured distance from a.

    Column pivoting takes the same steps whatever the threshold, so that the factors of the smallest one hold the others'
    as their first columns: the norm of the columns that are left off, as X is orthonormal, says how many. Where the
    smallest threshold keeps a full tile, or a tile of the first columns is not within its threshold, it is worked out by itself.
    """

    def measured(t: Tile) -> tuple[Tile, float]:
        return t, float(np.linalg.norm(a - t.dense()))

    low = compress(a, min(eps))
    least = measured(low)
    if low.w is None:
        return [least if e == min(eps) else measured(compress(a, e)) for e in eps]
    left = np.sqrt(np.append(np.cumsum((low.w * low.w).sum(axis=0)[::-1])[::-1], 0.0) + least[1] ** 2)
    out = []
    for e in eps:
        k = low.rank if e == min(eps) else int(np.flatnonzero(left <= max(e, left[-1]))[0])
        found = least if k == low.rank else measured(Tile(low.x[:, :k], low.w[:, :k]))
        out.append(found if found[1] <= e or found is least else measured(compress(a, e)))
    return out


def compress_each(a: np.ndarray, eps: tuple[float, ...]) -> list[tuple[str, int, float]]:
    """Form, rank and measured error of compress(a, e) for each threshold."""
    return [(t.kind, t.rank, err) for t, err in compress_all(a, eps)]


def settle(t: Tile) -> Tile:
    """t in full form if its rank is past half."""
    return t if t.w is None or keeps_low(t.rank, *t.shape) else Tile(t.dense())


def recompress(t: Tile, eps: float) -> Tile:
    """t with the least rank within eps: QR of both factors, then a pivoted QR of the small core between them."""
    if t.w is None:
        return compress(t.x, eps) if eps > 0 else t
    if not t.rank:
        return t
    qx, rx = np.linalg.qr(t.x)
    qw, rw = np.linalg.qr(t.w)
    found = pivoted_qr(rx @ rw.T, eps, min(t.shape) // 2)
    return Tile(qx @ found[0], qw @ found[1]) if found else Tile(t.dense())


def multiply(a: Tile, b: Tile) -> Tile:
    """a b. Between two low-rank tiles the middle factor goes to the side of the smaller rank."""
    if a.w is None and b.w is None:
        return Tile(a.x @ b.x)
    if a.w is None:
        return Tile(a.x @ b.x, b.w)
    if b.w is None:
        return Tile(a.x, b.x.T @ a.w)
    middle = a.w.T @ b.x
    return Tile(a.x @ middle, b.w) if b.rank <= a.rank else Tile(a.x, b.w @ middle.T)


def add(a: Tile, b: Tile) -> Tile:
    """a + b; low-rank factors stand side by side, so that the ranks add up."""
    if a.w is None or b.w is None:
        return Tile(a.dense() + b.dense())
    return Tile(np.hstack([a.x, b.x]), np.hstack([a.w, b.w]))


def product_flops(a: Tile, b: Tile) -> int:
    """Multiplications and additions of multiply(a, b)."""
    m, k, n = a.shape[0], a.shape[1], b.shape[1]
    if a.w is None and b.w is None:
        return 2 * m * k * n
    if a.w is None:
        return 2 * m * k * b.rank
    if b.w is None:
        return 2 * k * n * a.rank
    return 2 * k * a.rank * b.rank + 2 * (m if b.rank <= a.rank else n) * a.rank * b.rank


@dataclass
class Entries:
    """A full tile by its entries: rows, columns, values."""

    shape: tuple[int, int]
    i: np.ndarray
    j: np.ndarray
    v: np.ndarray

    def dense(self) -> np.ndarray:
        a = np.zeros(self.shape)
        a[self.i, self.j] = self.v
        return a


#: Pairs of entries that are multiplied at once.
PAIRS = 1 << 20


def joined(parts: list[tuple[int, np.ndarray, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Summed index, other index and values of several tiles of one block row or column, by the summed index. parts: where
    the summed index of a tile starts, its own summed indices, the others, the values."""
    k = np.concatenate([start + k for start, k, _, _ in parts])
    order = np.argsort(k, kind="stable")
    return k[order], np.concatenate([o for _, _, o, _ in parts])[order], np.concatenate([v for _, _, _, v in parts])[order]


def entry_products(left: tuple, right: tuple, n: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places (row n + column) and products of all pairs of entries of joined tiles that meet in the summed index, PAIRS or a
    few more at a time. No place is worked out that no pair adds to."""
    k, i, v = left
    k2, j, v2 = right
    first = np.searchsorted(k2, k, "left")
    many = np.searchsorted(k2, k, "right") - first
    met = np.flatnonzero(many)
    first, many, i, v = first[met], many[met], i[met].astype(np.int64) * n, v[met]
    ends = np.cumsum(many)
    at = 0
    while at < len(many):
        to = max(at + 1, int(np.searchsorted(ends, ends[at] + PAIRS)))
        size, last = many[at:to], ends[at:to]
        take = np.repeat(first[at:to] - (last - size) + last[0] - size[0], size) + np.arange(last[-1] - last[0] + size[0])
        yield np.repeat(i[at:to], size) + j[take], np.repeat(v[at:to], size) * v2[take]
        at = to


class Sum:
    """A running sum of tiles. Low-rank terms stand side by side until their joint rank passes half of the full rank; from
    then on the sum is full, and the result is compressed once, which costs less than a recompression for every few terms."""

    def __init__(self, eps: float = 0.0):
        self.eps, self.tile = eps, None

    def take(self, t: Tile) -> None:
        if self.tile is None:
            self.tile = Tile(t.x.copy(), t.w)
        elif self.tile.w is None:
            self.tile.x += t.dense()
        else:
            self.tile = settle(add(self.tile, t))
            if self.tile.w is None:
                self.tile = Tile(np.array(self.tile.x))

    def add_at(self, shape: tuple[int, int], places: np.ndarray, values: np.ndarray) -> None:
        """Values at places (row times columns, and column); the sum is full from then on."""
        if self.tile is None:
            self.tile = Tile(np.zeros(shape))
        elif self.tile.w is not None or not self.tile.x.flags.c_contiguous:
            self.tile = Tile(np.array(self.tile.dense(), order="C"))
        np.add.at(self.tile.x.reshape(-1), places, values)

    def result(self) -> Tile:
        return recompress(self.tile, self.eps) if self.eps > 0 else settle(self.tile)


def sparse_columns(a: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Doubly compressed columns: the columns that have entries, where each starts, row numbers, values."""
    j, i = np.nonzero(a.T)
    columns, starts = np.unique(j, return_index=True)
    return columns, np.append(starts, len(j)), i, a[i, j]


def sparse_multiply(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """a b over the entries of both: each entry of b pulls the column of a that it meets."""
    jc, cp, ir, num = sparse_columns(a)
    k, j = np.nonzero(b)
    at = np.searchsorted(jc, k)
    hit = (at < len(jc)) & (jc[np.minimum(at, max(len(jc) - 1, 0))] == k) if len(jc) else np.zeros(len(k), bool)
    at, k, j = at[hit], k[hit], j[hit]
    sizes = cp[at + 1] - cp[at]
    take = np.repeat(cp[at] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())
    out = np.zeros((a.shape[0], b.shape[1]))
    np.add.at(out, (ir[take], np.repeat(j, sizes)), num[take] * np.repeat(b[k, j], sizes))
    return out
