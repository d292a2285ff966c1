"""A small logical layer over operators, rewritten before any table is touched.

Expressions are applied to panels; four rewrites come first:
1. the transpose of a self-adjoint operator is the operator;
2. shifts and scales fold into one (alpha, gamma) on the product below them;
3. the Gram operator of a table with many rows and few features is applied as
   X'(X V) and not formed;
4. neighbouring column choices and rotations of a panel merge into one kernel.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np


@dataclass(frozen=True)
class Expr:
    """An operator expression."""

    def __add__(self, other: Expr) -> Expr:
        return Sum(self, other)

    def __mul__(self, factor: float) -> Expr:
        return Scale(self, float(factor))

    __rmul__ = __mul__

    def shift(self, gamma: float) -> Expr:
        return Shift(self, float(gamma))

    @property
    def t(self) -> Expr:
        return Transpose(self)


@dataclass(frozen=True)
class Leaf(Expr):
    """A self-adjoint operator held by a space."""

    space: object
    name: str = "A"


@dataclass(frozen=True)
class Gram(Expr):
    """X'X of a table's feature column."""

    df: object
    features: str
    rows: int
    d: int
    name: str = "X"


@dataclass(frozen=True)
class Implicit(Expr):
    """A Gram operator applied as two products with the rows."""

    gram: Gram


@dataclass(frozen=True)
class Formed(Expr):
    """A Gram operator whose d x d matrix is made once."""

    gram: Gram


@dataclass(frozen=True)
class Shift(Expr):
    inner: Expr
    gamma: float


@dataclass(frozen=True)
class Scale(Expr):
    inner: Expr
    factor: float


@dataclass(frozen=True)
class Transpose(Expr):
    inner: Expr


@dataclass(frozen=True)
class Sum(Expr):
    left: Expr
    right: Expr


@dataclass(frozen=True)
class Fused(Expr):
    """alpha * (inner - gamma * I): one product and one panel update."""

    inner: Expr
    alpha: float
    gamma: float


#: Gram operators of more rows times features than this are not formed.
FORM_LIMIT = 50_000_000


def rewrite(e: Expr, limit: int = FORM_LIMIT) -> Expr:
    """The expression in the form in which it is applied."""
    if isinstance(e, Transpose):
        inner = e.inner
        if isinstance(inner, Sum):
            return rewrite(Sum(Transpose(inner.left), Transpose(inner.right)), limit)
        return rewrite(inner, limit)
    if isinstance(e, Gram):
        return Implicit(e) if e.rows * e.d > limit else Formed(e)
    if isinstance(e, Shift):
        inner = rewrite(e.inner, limit)
        if isinstance(inner, Fused):
            return replace(inner, gamma=inner.gamma + e.gamma / inner.alpha) if inner.alpha else Fused(inner, 1.0, e.gamma)
        return Fused(inner, 1.0, e.gamma)
    if isinstance(e, Scale):
        inner = rewrite(e.inner, limit)
        return replace(inner, alpha=inner.alpha * e.factor) if isinstance(inner, Fused) else Fused(inner, e.factor, 0.0)
    if isinstance(e, Sum):
        return Sum(rewrite(e.left, limit), rewrite(e.right, limit))
    return e


def apply(e: Expr, panel, limit: int = FORM_LIMIT):
    """The expression times a panel. Sums need panels that add, as arrays do."""
    e = rewrite(e, limit)
    return _apply(e, panel)


def _apply(e: Expr, panel):
    if isinstance(e, Fused):
        if isinstance(e.inner, Leaf):
            return e.inner.space.step(panel, None, e.alpha, 0.0, e.gamma)
        return e.alpha * _apply(e.inner, panel) - e.alpha * e.gamma * panel
    if isinstance(e, Leaf):
        return e.space.apply(panel)
    if isinstance(e, Sum):
        return _apply(e.left, panel) + _apply(e.right, panel)
    if isinstance(e, Implicit):
        from ..build.gram import GramOperator

        return GramOperator(e.gram.df, e.gram.features).apply(panel)
    if isinstance(e, Formed):
        from ..build.gram import gram

        a = np.zeros((e.gram.d, e.gram.d))
        for r in gram(e.gram.df, e.gram.features).collect():
            a[r["i"], r["j"]] = r["v"]
        return a @ panel
    raise TypeError(f"not an operator expression: {e!r}")


def explain(e: Expr, depth: int = 0) -> str:
    """One line for each node."""
    pad = "  " * depth
    if isinstance(e, Fused):
        return f"{pad}product alpha={e.alpha:g} gamma={e.gamma:g}\n{explain(e.inner, depth + 1)}"
    if isinstance(e, Sum):
        return f"{pad}sum\n{explain(e.left, depth + 1)}\n{explain(e.right, depth + 1)}"
    if isinstance(e, (Transpose, Shift, Scale)):
        return f"{pad}{type(e).__name__.lower()}\n{explain(e.inner, depth + 1)}"
    if isinstance(e, (Implicit, Formed)):
        return f"{pad}{'implicit' if isinstance(e, Implicit) else 'formed'} gram of {e.gram.name} ({e.gram.rows} x {e.gram.d})"
    return f"{pad}{getattr(e, 'name', type(e).__name__)}"


@dataclass(frozen=True)
class PanelOps:
    """Column choices and rotations waiting to be done on a panel, as one matrix."""

    matrix: np.ndarray

    @staticmethod
    def start(k: int) -> PanelOps:
        return PanelOps(np.eye(k))

    def columns(self, at) -> PanelOps:
        return PanelOps(self.matrix[:, np.asarray(at, int)])

    def rotate(self, m: np.ndarray) -> PanelOps:
        return PanelOps(self.matrix @ m)

    def run(self, space, panel):
        """One kernel over the panel, a plain choice of columns where that is all there is."""
        m = self.matrix
        chosen = (m != 0).sum(0) == 1
        if chosen.all() and np.isin(m, (0, 1)).all():
            return space.columns(panel, m.argmax(0))
        return space.rotate(panel, m)
