"""Rules that decide a pair of clusters from summaries ``a`` and ``b``, without their points."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

_SLACK = 1e-9


def _between(a: str, b: str) -> Column:
    dx, dy = F.col(f"{a}.mx") - F.col(f"{b}.mx"), F.col(f"{a}.my") - F.col(f"{b}.my")
    return F.sqrt(dx * dx + dy * dy)


def far(a: str, b: str, limit: Column, rule: str = "hull") -> Column:
    """True only where the Hausdorff distance is above ``limit``.

    ``'printed'``: means farther apart than the limit and both radii allow. ``'hull'``: means lie in the convex
    hulls, and hulls are no farther apart than their points, so the smaller radius is enough.
    """
    if rule == "printed":
        reach = F.col(f"{a}.r") + F.col(f"{b}.r")
    elif rule == "hull":
        reach = F.least(F.col(f"{a}.r"), F.col(f"{b}.r"))
    else:
        raise ValueError("rule is 'hull' or 'printed'")
    return _between(a, b) > (limit + reach) * (1 + _SLACK)


def near(a: str, b: str, limit: Column, rule: str = "sound") -> Column:
    """True where the summaries already show a distance of at most ``limit``.

    ``'sound'`` uses the mean squared distance to the mean: some point of the other cluster is within that of its
    mean, on either side of any point. ``'printed'`` takes a mean for a point of its cluster and can be wrong.
    """
    gap = _between(a, b)
    ra, rb, va, vb = (F.col(f"{s}.{c}") for c in ("r", "var") for s in (a, b))
    if rule == "printed":
        return gap + F.greatest(ra, rb) <= limit
    if rule != "sound":
        raise ValueError("rule is 'sound' or 'printed'")
    square = lambda v: v * v
    return F.greatest(square(gap + ra) + vb, square(gap + rb) + va) <= square(limit) * (1 - _SLACK)
