"""Walks. A walk is an immutable tuple of steps; it is a value that can be named, bound, composed and applied to any start."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass


@dataclass(frozen=True)
class Step:
    op: str
    args: tuple = ()

    def __str__(self) -> str:
        return f"{self.op}({', '.join(map(str, self.args))})"


class BindError(ValueError):
    """A step that cannot follow its predecessor, an unbounded loop, a mark that was never set."""


@dataclass(frozen=True)
class Walk:
    """Composable traversal over multisets. Methods append one step; `>>` composes, left first."""

    steps: tuple[Step, ...] = ()

    def _then(self, op: str, *args) -> Walk:
        return Walk((*self.steps, Step(op, args)))

    def then(self, other: Walk) -> Walk:
        return Walk(self.steps + other.steps)

    __rshift__ = then

    # single steps
    def out_edges(self, *labels: str) -> Walk:
        return self._then("edges", "out", labels)

    def in_edges(self, *labels: str) -> Walk:
        return self._then("edges", "in", labels)

    def both_edges(self, *labels: str) -> Walk:
        return self._then("edges", "both", labels)

    def tail(self) -> Walk:
        """From edges to the vertices they leave."""
        return self._then("end", "src")

    def head(self) -> Walk:
        """From edges to the vertices they enter."""
        return self._then("end", "dst")

    def other(self) -> Walk:
        """From edges of `both_edges` to the far vertex."""
        return self._then("end", "far")

    def values(self, key: str) -> Walk:
        return self._then("values", key)

    # filters
    def keep_label(self, *labels: str) -> Walk:
        return self._then("label", True, labels)

    def drop_label(self, *labels: str) -> Walk:
        return self._then("label", False, labels)

    def keep(self, key: str, op: str, value=None) -> Walk:
        return self._then("property", True, key, op, value)

    def drop(self, key: str, op: str, value=None) -> Walk:
        """The exact complement of keep: elements without the property pass."""
        return self._then("property", False, key, op, value)

    def keep_element(self, ids: Iterable[int]) -> Walk:
        return self._then("element", True, tuple(ids))

    def drop_element(self, ids: Iterable[int]) -> Walk:
        return self._then("element", False, tuple(ids))

    # marks
    def mark(self, name: str) -> Walk:
        return self._then("mark", name)

    def keep_marked(self, name: str) -> Walk:
        return self._then("marked", True, name)

    def drop_marked(self, name: str) -> Walk:
        return self._then("marked", False, name)

    # hops: edge step and vertex step in one
    def out(self, *labels: str) -> Walk:
        return self.out_edges(*labels).head()

    def into(self, *labels: str) -> Walk:
        return self.in_edges(*labels).tail()

    def both(self, *labels: str) -> Walk:
        return self.both_edges(*labels).other()

    # control
    def power(self, n: int) -> Walk:
        """This walk n times."""
        return Walk(self.steps * n)

    def repeat(self, body: Walk, emit: str = "last", max_depth: int | None = None) -> Walk:
        """Apply body until nothing is left; emit 'last' (where it stops) or 'all' (every round). Needs max_depth unless body walks trees only."""
        return self._then("repeat", body, emit, max_depth)

    def branch(self, key: str, op: str, value, then: Walk, otherwise: Walk) -> Walk:
        """Exclusive arms by a property."""
        return self._then("branch", key, op, value, then, otherwise)

    def overlay(self, *arms: Walk) -> Walk:
        """Multiset sum of walks from the same place."""
        return self._then("overlay", arms)

    def intersect(self, arm: Walk, distinct: bool = False) -> Walk:
        return self._then("meet", arm, distinct)

    def minus(self, arm: Walk, distinct: bool = False) -> Walk:
        return self._then("minus", arm, distinct)

    def dedup(self) -> Walk:
        return self._then("dedup")

    def rank(self, k: int | None = None) -> Walk:
        """Order by repetition, then id; the first k, per origin if the run keeps origins."""
        return self._then("rank", k)

    def sample(self, fraction: float, seed: int = 0) -> Walk:
        """A fixed pseudo-random share of the elements, by hash."""
        return self._then("sample", fraction, seed)

    def sample_out(self, label: str, k: int, seed: int = 0) -> Walk:
        """k pseudo-random outgoing edges of each position; then heads."""
        return self._then("sample_out", label, k, seed).head()

    def sample_in(self, label: str, k: int, seed: int = 0) -> Walk:
        """k pseudo-random incoming edges of each position; then tails. Runs that keep origins choose for each origin on its own."""
        return self._then("sample_in", label, k, seed).tail()

    def simple_path(self) -> Walk:
        return self._then("simple_path")

    def unit(self) -> Walk:
        """Forget repetition so far: every traverser counts once."""
        return self._then("unit")

    def __str__(self) -> str:
        return " ".join(map(str, self.steps)) or "here"


def compose(*walks: Walk) -> Walk:
    """compose(b, a) applies a first: the right-to-left reading of function composition."""
    out = Walk()
    for w in reversed(walks):
        out = out >> w
    return out


def partial(method: Callable[..., Walk], *args) -> Callable[[Walk], Walk]:
    """A step with its argument fixed, to be applied to a walk later."""
    return lambda walk: method(walk, *args)


HERE = Walk()


def marks_used(steps: Iterable[Step]) -> set[str]:
    """Names that these steps compare with, arms and loops included."""
    used = set()
    for s in steps:
        if s.op == "marked":
            used.add(s.args[1])
        for w in inner_walks(s):
            used |= marks_used(w.steps)
    return used


def inner_walks(step: Step) -> list[Walk]:
    """Arms and bodies of one step."""
    return [w for a in step.args for w in (a if isinstance(a, tuple) else (a,)) if isinstance(w, Walk)]


def kind_after(walk: Walk, kind: str = "V", marks: frozenset[str] = frozenset()) -> str:
    """Binding: the kind of element (V, E or S) after the walk; raises where a step does not fit.

    `marks`: names set before. Marks set inside an arm or a body end with it.
    """
    marks = set(marks)
    for s in walk.steps:
        if s.op == "edges":
            kind = _need(s, kind, "V", "E")
        elif s.op in ("sample_out", "sample_in"):
            kind = _need(s, kind, "V", "E")
        elif s.op == "end":
            kind = _need(s, kind, "E", "V")
        elif s.op == "label":
            kind = _need(s, kind, "E", "E")
        elif s.op == "values":
            kind = _need(s, kind, "VE", "S")
        elif s.op in ("property", "properties", "element"):
            kind = _need(s, kind, "VE", kind)
        elif s.op == "mark":
            marks.add(s.args[0])
        elif s.op == "marked" and s.args[1] not in marks | {"origin"}:
            raise BindError(f"{s}: the mark was never set")
        elif s.op == "repeat":
            _need(s, kind, "V", "V")
            if kind_after(s.args[0], "V", marks) != "V":
                raise BindError(f"{s}: the body must lead from vertices to vertices")
        elif s.op == "branch":
            a, b = kind_after(s.args[3], kind, marks), kind_after(s.args[4], kind, marks)
            if a != b:
                raise BindError(f"{s}: the arms end in {a} and {b}")
            kind = a
        elif s.op == "overlay":
            ends = {kind_after(a, kind, marks) for a in s.args[0]}
            if len(ends) != 1:
                raise BindError(f"{s}: the arms end in {sorted(ends)}")
            kind = ends.pop()
        elif s.op in ("meet", "minus") and kind_after(s.args[0], kind, marks) != kind:
            raise BindError(f"{s}: the arm must end in {kind}")
    return kind


def _need(step: Step, kind: str, allowed: str, after: str) -> str:
    if kind not in allowed:
        raise BindError(f"{step} needs {' or '.join(allowed)}, not {kind}")
    return after
