"""The coordinate kernel: products of blocks given as rows, columns and values."""

from __future__ import annotations

import numpy as np

from roundmm.functions.semiring import Semiring

Cells = tuple[np.ndarray, np.ndarray, np.ndarray]


def coo_product(a: tuple, b: tuple, semiring: Semiring, area: int, extra: tuple | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sparse block product of coordinate triples, and ``extra`` cells added: B sorted by row, each entry of A meets its run; equal cells are merged."""
    ar, ac, av = a
    br, bc, bv = b
    if (br[1:] < br[:-1]).any():
        order = np.argsort(br, kind="stable")
        br, bc, bv = br[order], bc[order], bv[order]
    ac = ac.astype(br.dtype, copy=False)  # else the search copies the longer side
    wide = int(br[-1]) - int(br[0]) + 1 if len(br) else 0
    if 0 < wide <= 4 * len(ac):  # counts by inner coordinate cost less than a search
        inner = ac[(ac >= br[0]) & (ac <= br[-1])] - br[0]
        total = int(np.bincount(br - br[0], minlength=wide)[inner].sum())
        if total > AT_ONCE >> 6 and len(held := dense_product((ar, ac, av), (br, bc, bv), semiring, total, extra)):
            return held
    lo, hi = np.searchsorted(br, ac, "left"), np.searchsorted(br, ac, "right")
    many = hi - lo
    total = int(many.sum())

    def cells(x: slice) -> tuple:
        own = np.repeat(np.arange(x.start, x.stop), many[x])
        at = np.arange(len(own)) - np.repeat(np.cumsum(many[x]) - many[x], many[x]) + np.repeat(lo[x], many[x])
        return ar[own], bc[at], semiring.pair(av[own], bv[at])

    parts = [extra] if extra is not None else []
    if total <= AT_ONCE:
        parts.append(cells(slice(0, len(ac))))
    else:  # runs of rows of A, their products merged before the next ones are made
        order = np.argsort(ar, kind="stable")
        ar, av, lo, many = ar[order], av[order], lo[order], many[order]
        cut = np.flatnonzero(np.diff(np.cumsum(many) // AT_ONCE)) + 1
        for at, to in zip([0, *cut], [*cut, len(ar)], strict=True):
            parts.append(merged(*cells(slice(int(at), int(to))), semiring, area))
    return merged(*(np.concatenate(x) for x in zip(*parts, strict=True)), semiring, area)


#: Elementary products that the kernel holds at once, and cells of a block that it holds as a dense array.
AT_ONCE, DENSE = 1 << 20, 1 << 23


def dense_product(a: tuple, b: tuple, semiring: Semiring, total: int, extra: tuple | None = None) -> tuple:
    """The same by dense arrays and BLAS, where that is less work: sums of products, or zeros and ones of ``or_and``. Empty where it doesn't apply."""
    ring = semiring.merge is np.add and semiring.pair is np.multiply
    if not ring and not (semiring.name == "or_and" and (a[2] == 1).all() and (b[2] == 1).all()):
        return ()
    rows, cols = ([x[k], *([] if extra is None else [extra[k]])] for k, x in ((0, a), (1, b)))
    (r0, r1), (c0, c1) = ((min(int(x.min()) for x in y if len(x)), max(int(x.max()) for x in y if len(x)) + 1) for y in (rows, cols))
    k0, k1 = max(int(a[1].min()), int(b[0].min())), min(int(a[1].max()), int(b[0].max())) + 1
    h, w, k = r1 - r0, c1 - c0, k1 - k0
    if max(h * w, h * k, k * w) > DENSE or h * w * k + 32 * k * (h + w) > 1024 * total:
        return ()
    inner = (a[1] >= k0) & (a[1] < k1), (b[0] >= k0) & (b[0] < k1)
    kind = float if ring and not short(a[2], b[2], k) else np.float32
    x, y = np.zeros((h, k), kind), np.zeros((k, w), kind)
    left, right = (a[0][inner[0]] - r0, a[1][inner[0]] - k0), (b[0][inner[1]] - k0, b[1][inner[1]] - c0)
    x[left], y[right] = a[2][inner[0]], b[2][inner[1]]
    c = x @ y
    if (x >= 0).all() and (y >= 0).all() and a[2].all() and b[2].all() and np.isfinite(c).all() and min(a[2].min() * b[2].min(), 1.0) > 1e-300:
        hit = c > 0
    else:  # products may cancel: the cells reached are those of the patterns' product
        u, v = np.zeros((h, k), np.float32), np.zeros((k, w), np.float32)
        u[left] = v[right] = 1
        hit = u @ v > 0
    c = c.astype(float) if ring else hit.astype(float)
    if extra is not None:
        at = extra[0] - r0, extra[1] - c0
        c[at] = semiring.merge(c[at], extra[2])
        hit[at] = True
    cell = np.flatnonzero(hit)
    return cell // w + r0, cell % w + c0, c.ravel()[cell]


def short(x: np.ndarray, y: np.ndarray, k: int) -> bool:
    """Whether sums of ``k`` products of these values are whole numbers that float32 holds exactly."""
    top = max(abs(float(x.max())), abs(float(x.min()))) * max(abs(float(y.max())), abs(float(y.min()))) * k
    return top < 1 << 24 and (x == np.floor(x)).all() and (y == np.floor(y)).all()


def merged(r: np.ndarray, c: np.ndarray, v: np.ndarray, semiring: Semiring, area: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One entry a cell. Where the block's ``area`` isn't many times the entries they are added in an array of it, else sorted."""
    if not len(r):
        return r, c, v
    top, left = int(r.min()), int(c.min())
    width, height = int(c.max()) - left + 1, int(r.max()) - top + 1
    key = (r - top) * width + (c - left)
    if height * width <= min(8 * len(r), area):
        if semiring.merge is np.add:
            held = np.bincount(key, v, height * width)
        else:
            held = np.full(height * width, semiring.zero)
            semiring.merge.at(held, key, v)
        hit = np.zeros(height * width, bool)
        hit[key] = True
        cell = np.flatnonzero(hit)
        return cell // width + top, cell % width + left, held[cell]
    order = np.argsort(key, kind="stable")
    key, v = key[order], v[order]
    first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
    cell = key[first]
    return cell // width + top, cell % width + left, semiring.merge.reduceat(v, first)
