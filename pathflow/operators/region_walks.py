"""The five functions of the region flow graph as walks of the step algebra, and their composition.

They read boxes and `sub` edges only, so they run on any region graph, regular or hand-made. An edge carries the corners and the type of its child: what
fails is dropped on the edge, before the hop is made.
"""

from __future__ import annotations

from ..functions.regions import checked
from ..plans.traversal import HERE, Walk


def meets(rect) -> Walk:
    """Keep what overlaps the rectangle: four property filters."""
    x0, y0, x1, y1 = checked(rect)
    return HERE.keep("bl_x", "<=", x1).keep("bl_y", "<=", y1).keep("tr_x", ">=", x0).keep("tr_y", ">=", y0)


def inside(rect) -> Walk:
    """g: keep what lies wholly in the rectangle."""
    x0, y0, x1, y1 = checked(rect)
    return HERE.keep("bl_x", ">=", x0).keep("bl_y", ">=", y0).keep("tr_x", "<=", x1).keep("tr_y", "<=", y1)


def descend_free() -> Walk:
    """h: child quads, untested."""
    return HERE.out_edges("sub").keep("type", "=", "quad").head()


def descend_open(rect) -> Walk:
    """f: child quads that overlap."""
    return HERE.out_edges("sub").keep("type", "=", "quad") >> meets(rect).head()


def poi_free() -> Walk:
    """r: points of interest below, untested."""
    return HERE.out_edges("sub").keep("type", "=", "poi").head()


def poi_tested(rect) -> Walk:
    """s: points of interest below that overlap."""
    return HERE.out_edges("sub").keep("type", "=", "poi") >> meets(rect).head()


def star(step: Walk) -> Walk:
    """A place and all that repeating the step reaches."""
    return HERE.overlay(HERE, HERE.repeat(step, emit="all"))


def flow(rect) -> Walk:
    """The literal flow graph from the root: A by f, B by g and h, C = s(A) with r(B), repeats kept."""
    a = star(descend_open(rect))
    b = a >> inside(rect) >> star(descend_free())
    return HERE.overlay(a >> poi_tested(rect), b >> poi_free())
