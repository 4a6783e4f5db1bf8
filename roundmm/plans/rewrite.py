"""An expression tree of matrix operations, rewritten before it becomes DataFrames.

Transposes move to the leaves and cancel; scalars move out; slices move to the operands' rows and columns; masks move below
the aggregation of a product; chains of products are ordered by the work they are estimated to cost.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from roundmm.functions.schedule import ceil_div
from roundmm.model import MatrixFrame, to_blocks, to_coordinates
from roundmm.operators import elementwise as ew
from roundmm.operators.baselines import multiply_join


@dataclass(frozen=True)
class Expr:
    @property
    def shape(self) -> tuple[int, int]:
        raise NotImplementedError

    def __matmul__(self, other: Expr) -> Expr:
        return Product(self, other)

    def __add__(self, other: Expr) -> Expr:
        return Sum(self, other)

    @property
    def T(self) -> Expr:
        return Transposed(self)

    def scaled(self, by: float) -> Expr:
        return Scaled(self, by)

    def mask(self, pattern: MatrixFrame) -> Expr:
        return Masked(self, pattern)

    def rows(self, lo: int, hi: int) -> Expr:
        return Sliced(self, (lo, hi), None)

    def cols(self, lo: int, hi: int) -> Expr:
        return Sliced(self, None, (lo, hi))

    def power(self, k: int) -> Expr:
        """``k`` factors, by squaring: shared squares are computed once a use."""
        if k < 1:
            raise ValueError("a power needs k >= 1")
        if k == 1:
            return self
        half = self.power(k // 2)
        return half @ half if k % 2 == 0 else (half @ half) @ self

    def lower(self, method: str = "join", **options) -> MatrixFrame:
        return lower(optimize(self), method, **options)

    def plan(self) -> str:
        return describe(optimize(self))

    def explain_rounds(self, block: int, rho: int) -> str:
        """Each product of the optimised tree with its rounds, and the words that it shuffles at most."""
        lines: list[str] = []

        def walk(e: Expr) -> None:
            if isinstance(e, Product):
                walk(e.a)
                walk(e.b)
                (n, k), m = e.a.shape, e.b.shape[1]
                qi, qh, qj = (ceil_div(x, block) for x in (n, k, m))
                r = min(rho, qh)
                each = r * (qj * min(block, n) * min(block, k) * qi + qi * min(block, k) * min(block, m) * qj + n * m)
                lines.append(f"{describe(e)}: grid {qi}x{qh}x{qj}, {ceil_div(qh, r) + 1} rounds, at most {each} words a round")
            elif not isinstance(e, Leaf):
                walk(e.a)
                if isinstance(e, Sum):
                    walk(e.b)

        walk(optimize(self))
        return "\n".join(lines)


@dataclass(frozen=True)
class Leaf(Expr):
    m: MatrixFrame

    @property
    def shape(self) -> tuple[int, int]:
        return self.m.n_rows, self.m.n_cols

    @cached_property
    def entries(self) -> int:
        return self.m.df.count()


@dataclass(frozen=True)
class Product(Expr):
    a: Expr
    b: Expr

    @property
    def shape(self) -> tuple[int, int]:
        return self.a.shape[0], self.b.shape[1]


@dataclass(frozen=True)
class Sum(Expr):
    a: Expr
    b: Expr

    @property
    def shape(self) -> tuple[int, int]:
        return self.a.shape


@dataclass(frozen=True)
class Transposed(Expr):
    a: Expr

    @property
    def shape(self) -> tuple[int, int]:
        return self.a.shape[::-1]


@dataclass(frozen=True)
class Scaled(Expr):
    a: Expr
    by: float

    @property
    def shape(self) -> tuple[int, int]:
        return self.a.shape


@dataclass(frozen=True)
class Masked(Expr):
    a: Expr
    pattern: MatrixFrame

    @property
    def shape(self) -> tuple[int, int]:
        return self.a.shape


@dataclass(frozen=True)
class Sliced(Expr):
    a: Expr
    r: tuple[int, int] | None
    c: tuple[int, int] | None

    @property
    def shape(self) -> tuple[int, int]:
        return self.a.shape


def leaf(m: MatrixFrame) -> Expr:
    return Leaf(m)


def rewritten(e: Expr) -> Expr:
    """One pass from the leaves up."""
    match e:
        case Transposed(a):
            match rewritten(a):
                case Transposed(x):
                    return x
                case Product(x, y):
                    return Product(rewritten(Transposed(y)), rewritten(Transposed(x)))
                case Sum(x, y):
                    return Sum(rewritten(Transposed(x)), rewritten(Transposed(y)))
                case Scaled(x, by):
                    return Scaled(rewritten(Transposed(x)), by)
                case Leaf(m):
                    return Leaf(m.T)
                case other:
                    return Transposed(other)
        case Scaled(a, by):
            match rewritten(a):
                case Scaled(x, inner):
                    return Scaled(x, float(by) * inner) if _ordinary(x) else Scaled(Scaled(x, inner), by)
                case other:
                    return Scaled(other, by)
        case Sliced(a, r, c):
            match rewritten(a):
                case Product(x, y):
                    x = rewritten(Sliced(x, r, None)) if r else x
                    return Product(x, rewritten(Sliced(y, None, c)) if c else y)
                case Sum(x, y):
                    return Sum(rewritten(Sliced(x, r, c)), rewritten(Sliced(y, r, c)))
                case Leaf(m):
                    m = m.rows(*r) if r else m
                    return Leaf(m.cols(*c) if c else m)
                case other:
                    return Sliced(other, r, c)
        case Product(a, b):
            a, b = rewritten(a), rewritten(b)
            if isinstance(a, Scaled):
                return rewritten(Scaled(Product(a.a, b), a.by))
            if isinstance(b, Scaled):
                return rewritten(Scaled(Product(a, b.a), b.by))
            return Product(a, b)
        case Sum(a, b):
            a, b = rewritten(a), rewritten(b)
            if a == b and _ordinary(a):
                return rewritten(Scaled(a, 2.0))
            return Sum(a, b)
        case Masked(a, p):
            return Masked(rewritten(a), p)
    return e


def _ordinary(e: Expr) -> bool:
    """Whether the expression's numbers are added and multiplied as usual."""
    while not isinstance(e, Leaf):
        e = e.a
    return e.m.semiring.name in ("plus_times", "count")


def factors(e: Expr) -> list[Expr]:
    return factors(e.a) + factors(e.b) if isinstance(e, Product) else [e]


def density(e: Expr) -> float:
    """Estimated share of cells of an operand; leaves are counted."""
    rows, cols = e.shape
    match e:
        case Leaf():
            return min(1.0, e.entries / max(rows * cols, 1))
        case Product(a, b):
            return min(1.0, density(a) * density(b) * a.shape[1])
        case Sum(a, b):
            return min(1.0, density(a) + density(b))
    return density(e.a)


def ordered(e: Expr) -> Expr:
    """Chains of products in the order of least estimated work (dynamic programming over the chain)."""
    match e:
        case Product():
            f = [ordered(x) for x in factors(e)]
            if len(f) == 2:
                return Product(*f)
            n = len(f)
            best: dict[tuple[int, int], tuple[float, float, Expr]] = {(i, i): (0.0, density(f[i]), f[i]) for i in range(n)}
            for span in range(1, n):
                for i in range(n - span):
                    k = i + span
                    options = []
                    for cut in range(i, k):
                        (c1, d1, x), (c2, d2, y) = best[i, cut], best[cut + 1, k]
                        work = x.shape[0] * x.shape[1] * d1 * y.shape[1] * d2
                        options.append((c1 + c2 + work, min(1.0, d1 * d2 * x.shape[1]), Product(x, y)))
                    best[i, k] = min(options, key=lambda o: o[0])
            return best[0, n - 1][2]
        case Sum(a, b):
            return Sum(ordered(a), ordered(b))
        case Masked(a, p):
            return Masked(ordered(a), p)
        case Scaled(a, by):
            return Scaled(ordered(a), by)
        case Sliced(a, r, c):
            return Sliced(ordered(a), r, c)
        case Transposed(a):
            return Transposed(ordered(a))
    return e


def optimize(e: Expr, passes: int = 10) -> Expr:
    for _ in range(passes):
        after = rewritten(e)
        if after == e:
            break
        e = after
    return ordered(e)


def lower(e: Expr, method: str = "join", **options) -> MatrixFrame:
    """DataFrames of an expression. ``method``: ``join``, ``3d`` (needs ``block``, ``rho``) or ``sparse`` (``m``, ``rho``)."""
    match e:
        case Leaf(m):
            return m
        case Product(a, b):
            x, y = lower(a, method, **options), lower(b, method, **options)
            if method == "join":
                return multiply_join(x, y)
            if method == "3d":
                from roundmm.operators.dense3d import multiply_3d

                block = options["block"]
                return to_coordinates(multiply_3d(to_blocks(x, block, block).stored(), to_blocks(y, block, block).stored(), options.get("rho", "max")))
            if method == "sparse":
                from roundmm.operators.sparse3d import multiply_3d_sparse

                return multiply_3d_sparse(x, y, options["m"], options.get("rho", "max"), options.get("density", "flops_upper"))
            raise ValueError("method must be 'join', '3d' or 'sparse'")
        case Sum(a, b):
            return ew.add(lower(a, method, **options), lower(b, method, **options))
        case Scaled(a, by):
            return ew.scale(lower(a, method, **options), by)
        case Transposed(a):
            return lower(a, method, **options).T
        case Sliced(a, r, c):
            m = lower(a, method, **options)
            m = m.rows(*r) if r else m
            return m.cols(*c) if c else m
        case Masked(Product(a, b), p) if method == "join":
            return ew.masked_product(lower(a, method, **options), lower(b, method, **options), p)
        case Masked(a, p):
            return ew.mask(lower(a, method, **options), p)
    raise TypeError(type(e))


def describe(e: Expr) -> str:
    match e:
        case Leaf(m):
            return f"{m.n_rows}x{m.n_cols}"
        case Product(a, b):
            return f"({describe(a)} @ {describe(b)})"
        case Sum(a, b):
            return f"({describe(a)} + {describe(b)})"
        case Scaled(a, by):
            return f"{by} * {describe(a)}"
        case Transposed(a):
            return f"{describe(a)}.T"
        case Sliced(a, r, c):
            return f"{describe(a)}[{r}, {c}]"
        case Masked(a, _):
            return f"mask({describe(a)})"
    raise TypeError(type(e))
