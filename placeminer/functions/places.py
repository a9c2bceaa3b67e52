"""Place functions over columns. A place is two sorted arrays without repeats."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

START, END = "__START__", "__END__"


def _col(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def side(activities: Column | str) -> Column:
    """A side in canonical form."""
    return F.array_sort(F.array_distinct(_col(activities)))


def place_id(pre: Column | str, post: Column | str) -> Column:
    """Canonical id ``a,b>c`` of a place (L1)."""
    text = lambda x: F.concat_ws(",", F.transform(side(x), lambda a: a.cast("string")))
    return F.concat(text(pre), F.lit(">"), text(post))


def make(pre: Column | str, post: Column | str) -> Column:
    """A place struct (L1)."""
    return F.struct(place_id(pre, post).alias("place_id"), side(pre).alias("pre"), side(post).alias("post"), depth(pre, post).alias("depth"))


def selfloops(pre: Column | str, post: Column | str) -> Column:
    """Activities on both sides (L2)."""
    return F.array_sort(F.array_intersect(_col(pre), _col(post)))


def is_through(pre: Column | str, post: Column | str) -> Column:
    """Both sides non-empty (L2)."""
    return (F.size(_col(pre)) > 0) & (F.size(_col(post)) > 0)


def depth(pre: Column | str, post: Column | str) -> Column:
    """Number of arcs (L2)."""
    return F.size(F.array_distinct(_col(pre))) + F.size(F.array_distinct(_col(post)))


def _subset(a: Column, b: Column) -> Column:
    return F.size(F.array_except(a, b)) == 0


def is_pre_expansion(p_pre, p_post, q_pre, q_post, direct: bool = False) -> Column:
    """Whether p is a preset expansion of q: a strictly larger preset and the same postset (L3)."""
    p_pre, p_post, q_pre, q_post = map(_col, (p_pre, p_post, q_pre, q_post))
    grown = F.size(F.array_except(p_pre, q_pre))
    more = (grown == 1) if direct else (grown >= 1)
    return _subset(q_pre, p_pre) & more & _subset(p_post, q_post) & _subset(q_post, p_post)


def is_post_expansion(p_pre, p_post, q_pre, q_post, direct: bool = False) -> Column:
    """Whether p is a postset expansion of q (L3)."""
    return is_pre_expansion(p_post, p_pre, q_post, q_pre, direct)


def support_size(pre: Column | str, post: Column | str) -> Column:
    """Number of activities on either side (L4)."""
    return F.size(F.array_union(_col(pre), _col(post)))


def wires(pre: Column | str, post: Column | str) -> Column:
    """Array of structs (a, b): all pairs that the place connects."""
    return F.flatten(F.transform(_col(pre), lambda a: F.transform(_col(post), lambda b: F.struct(a.alias("a"), b.alias("b")))))


def effect(pre: Column | str, post: Column | str) -> Column:
    """Net effect: what only produces and what only consumes (L6). Places of one effect always hold equal tokens."""
    return F.struct(F.array_sort(F.array_except(_col(pre), _col(post))).alias("gain"), F.array_sort(F.array_except(_col(post), _col(pre))).alias("loss"))
