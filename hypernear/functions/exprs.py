"""Column expressions for margins and bounds.

Dot products are left folds in component order. With a known small dimension they are written out, so that
they stay inside whole-stage code generation; otherwise they are a higher-order fold. Both give the same bits.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

UNROLL = 160  # larger dimensions would outgrow one generated method


def dot(a: Column, b: Column, d: int | None = None) -> Column:
    """Inner product of two DOUBLE arrays."""
    if d is not None and 0 < d <= UNROLL:
        total = F.get(a, F.lit(0)) * F.get(b, F.lit(0))
        for i in range(1, d):
            total = total + F.get(a, F.lit(i)) * F.get(b, F.lit(i))
        return total
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def norm(a: Column, d: int | None = None) -> Column:
    return F.sqrt(dot(a, a, d))


def absdot(x: Column, q: Column, d: int | None = None) -> Column:
    """Margin of an augmented point from a plane with a unit normal."""
    return F.abs(dot(x, q, d))


def margin(p: Column, q: Column) -> Column:
    """Margin of a raw point: the plane's last coefficient is its offset, and its normal may have any length."""
    size = F.size(p)
    normal = F.slice(q, F.lit(1), size)
    return F.abs(dot(p, normal) + F.get(q, size)) / norm(normal)


def augment(p: Column) -> Column:
    return F.concat(p, F.array(F.lit(1.0)))


def normal_of(q: Column) -> Column:
    return F.slice(q, F.lit(1), F.size(q) - 1)


def rescale(q: Column) -> Column:
    """The same plane with a unit normal."""
    length = norm(normal_of(q))
    return F.transform(q, lambda v: v / length)


def node_bound(ip: Column, q_norm: Column, radius: Column) -> Column:
    """No point of a ball lies nearer: ip is the plane's product with the centre."""
    return F.greatest(F.abs(ip) - q_norm * radius, F.lit(0.0))


def point_ball_bound(ip: Column, q_norm: Column, r_x: Column) -> Column:
    """The same with a point's own distance from the leaf centre."""
    return node_bound(ip, q_norm, r_x)


def query_parts(ip: Column, c_norm: Column, q_norm: Column) -> tuple[Column, Column]:
    """The plane's components along and across the centre."""
    along = ip / c_norm
    return along, F.sqrt(F.greatest(q_norm * q_norm - along * along, F.lit(0.0)))


def point_cone_bound(ip: Column, c_norm: Column, q_norm: Column, x_par: Column, x_perp: Column) -> Column:
    """No point with these components along and across the centre lies nearer.

    Turning such a point about the centre moves its product between plus and minus; where both have one sign the
    nearer end bounds the margin, and where they differ the plane can be met.
    """
    along, across = query_parts(ip, c_norm, q_norm)
    least = along * x_par - across * x_perp
    most = along * x_par + across * x_perp
    return F.when(least > 0, least).when(most < 0, -most).otherwise(F.lit(0.0))


def cone_slack(q_norm: Column, x_par: Column, x_perp: Column) -> Column:
    """What rounding may take from the cone bound."""
    return F.lit(1e-7) * q_norm * F.sqrt(x_par * x_par + x_perp * x_perp)


def sibling_ip(ip_parent: Column, ip_child: Column, n_parent: Column, n_child: Column) -> Column:
    """Product with the other child's centre: the parent's centre is the mean of both, weighted by their counts."""
    return (n_parent * ip_parent - n_child * ip_child) / (n_parent - n_child)


def box_bound(lo: Column, hi: Column, q: Column) -> Column:
    """No point of an axis-parallel box lies nearer: interval arithmetic by component."""
    zero = F.lit(0.0)
    low = F.aggregate(F.zip_with(F.arrays_zip(lo.alias("lo"), hi.alias("hi")), q, lambda b, w: F.when(w >= 0, b["lo"] * w).otherwise(b["hi"] * w)), zero, lambda s, v: s + v)
    high = F.aggregate(F.zip_with(F.arrays_zip(lo.alias("lo"), hi.alias("hi")), q, lambda b, w: F.when(w >= 0, b["hi"] * w).otherwise(b["lo"] * w)), zero, lambda s, v: s + v)
    return F.when(low > 0, low).when(high < 0, -high).otherwise(zero)


def prune_slack(q_norm: Column, c_norm: Column) -> Column:
    """Rounding of centre products, so that no tied answer is pruned."""
    return F.lit(1e-9) * q_norm * F.greatest(F.lit(1.0), c_norm)
