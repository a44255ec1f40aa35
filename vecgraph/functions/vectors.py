"""Vector algebra and the theory of compared distances as Column expressions over array<double>.

Sums fold from left to right in double, so that other engines get the same bits. These forms are for narrow use and for checking;
bulk work goes through the Arrow kernels of vecgraph.operators."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

Vec = Column | str


def _c(x: Vec) -> Column:
    return F.col(x) if isinstance(x, str) else x


def _fold(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, x: acc + x)


def dot(a: Vec, b: Vec) -> Column:
    return _fold(F.zip_with(_c(a), _c(b), lambda x, y: x * y))


def norm_sq(a: Vec) -> Column:
    return dot(a, a)


def l2_sq(a: Vec, b: Vec) -> Column:
    return _fold(F.zip_with(_c(a), _c(b), lambda x, y: (x - y) * (x - y)))


def l2(a: Vec, b: Vec) -> Column:
    return F.sqrt(l2_sq(a, b))


def cosine(a: Vec, b: Vec) -> Column:
    """Cosine similarity; null when a vector is zero."""
    size = F.sqrt(norm_sq(a)) * F.sqrt(norm_sq(b))
    return F.when(size > 0, dot(a, b) / size)


def vsub(a: Vec, b: Vec) -> Column:
    return F.zip_with(_c(a), _c(b), lambda x, y: x - y)


def vadd(a: Vec, b: Vec) -> Column:
    return F.zip_with(_c(a), _c(b), lambda x, y: x + y)


def vscale(a: Vec, factor: float | Column) -> Column:
    f = F.lit(float(factor)) if isinstance(factor, int | float) else factor
    return F.transform(_c(a), lambda x: x * f)


def vslice(a: Vec, start: int, length: int) -> Column:
    """Dimensions start .. start + length - 1, counted from 0."""
    return F.slice(_c(a), start + 1, length)


def vconcat(*parts: Vec) -> Column:
    return F.concat(*map(_c, parts))


def error_vector(x: Vec, decoded: Vec) -> Column:
    """What a codec loses: the vector minus its decoded form."""
    return vsub(x, decoded)


def bisector_margin(u: Vec, v: Vec, w: Vec) -> Column:
    """Which side of the bisector of v and w the vertex u lies on: negative if v is nearer, positive if w is, 0 on it."""
    return dot(vsub(w, v), u) - (norm_sq(w) - norm_sq(v)) / 2


def comparison_error(u: Vec, v: Vec, w: Vec, eu: Vec, ev: Vec, ew: Vec, asymmetric: bool = False) -> Column:
    """By how much the margin changes when u, v, w are replaced by their decoded forms; with `asymmetric` u stays as it is."""
    total = dot(ew, u) - dot(ev, u) - dot(w, ew) + dot(v, ev) + (norm_sq(ew) - norm_sq(ev)) / 2
    return total if asymmetric else total + dot(vsub(w, v), eu) - dot(ew, eu) + dot(ev, eu)


def admits_candidate(u: Vec, farthest: Vec, w: Vec) -> Column:
    """Candidate acquisition: w is nearer to the inserted u than the farthest candidate."""
    return bisector_margin(u, farthest, w) > 0


def is_occluded(candidate: Vec, inserted: Vec, selected: Vec) -> Column:
    """Neighbour selection: the candidate is nearer to a selected neighbour than to the inserted vertex."""
    return bisector_margin(candidate, inserted, selected) > 0
