"""Small-state problems on trees, each as a handful of small tables over (max,+).

A vertex holds a vector over states. `init` gives it before any child is known;
a child's vector is `lifted` over its edge and then `joined` in. Helpers of the
binary extension hold the partial vector of the vertex they stand for, so the
edge above a helper lifts by identity. Minimisation is maximisation of negated
weights.
"""

from __future__ import annotations

from dataclasses import dataclass, field

NODE, EDGE = "node", "edge"


@dataclass(frozen=True)
class Problem:
    name: str
    states: tuple[str, ...]
    #: state -> 0, NODE (the vertex's weight) or absent (impossible), before any child.
    init: dict[str, object]
    #: (child state, state it becomes at the parent, 0 or EDGE).
    lift: tuple[tuple[str, str, object], ...]
    #: (state, state, joint state); order does not matter.
    join: tuple[tuple[str, str, str], ...]
    final: tuple[str, ...]
    sense: str = "max"
    #: as init, for helpers; by default as init with weight 0.
    init_helper: dict[str, object] | None = None
    #: weights replaced by 1 (cardinality problems).
    unit: bool = False
    notes: str = field(default="", compare=False)

    @property
    def helper_init(self) -> dict[str, object]:
        return self.init_helper if self.init_helper is not None else {s: 0 for s in self.init}


def _same(states: str) -> tuple[tuple[str, str, str], ...]:
    return tuple((s, s, s) for s in states)


def matching(unit: bool = False) -> Problem:
    """Heaviest set of edges without a common end. U: the vertex is free, M: matched to a child."""
    return Problem(
        "maximum_matching" if unit else "maximum_weight_matching",
        ("U", "M"),
        {"U": 0},
        (("U", "U", 0), ("M", "U", 0), ("U", "M", EDGE)),
        (("U", "U", "U"), ("U", "M", "M"), ("M", "U", "M")),
        ("U", "M"),
        unit=unit,
    )


def vertex_cover(unit: bool = False) -> Problem:
    """Lightest set of vertices that touches every edge. I: in, O: out."""
    return Problem(
        "minimum_vertex_cover", ("I", "O"), {"I": NODE, "O": 0}, (("I", "I", 0), ("O", "I", 0), ("I", "O", 0)), _same("IO"), ("I", "O"), sense="min", unit=unit
    )


def independent_set(unit: bool = False) -> Problem:
    """Heaviest set of vertices without an edge inside. I: in, O: out."""
    return Problem(
        "maximum_independent_set", ("I", "O"), {"I": NODE, "O": 0}, (("O", "I", 0), ("I", "O", 0), ("O", "O", 0)), _same("IO"), ("I", "O"), unit=unit
    )


def dominating_set(unit: bool = False) -> Problem:
    """Lightest set that holds or neighbours every vertex. I: in, D: dominated by a child, N: not yet."""
    return Problem(
        "minimum_dominating_set",
        ("I", "D", "N"),
        {"I": NODE, "N": 0},
        (("I", "I", 0), ("D", "I", 0), ("N", "I", 0), ("I", "D", 0), ("D", "N", 0)),
        (("I", "I", "I"), ("N", "N", "N"), ("D", "D", "D"), ("D", "N", "D"), ("N", "D", "D")),
        ("I", "D"),
        sense="min",
        init_helper={"I": 0, "N": 0},
        unit=unit,
    )


def independent_dominating_set(unit: bool = False) -> Problem:
    """Lightest dominating set without an edge inside."""
    return Problem(
        "minimum_independent_dominating_set",
        ("I", "D", "N"),
        {"I": NODE, "N": 0},
        (("D", "I", 0), ("N", "I", 0), ("I", "D", 0), ("D", "N", 0)),
        (("I", "I", "I"), ("N", "N", "N"), ("D", "D", "D"), ("D", "N", "D"), ("N", "D", "D")),
        ("I", "D"),
        sense="min",
        init_helper={"I": 0, "N": 0},
        unit=unit,
    )


def edge_cover(unit: bool = False) -> Problem:
    """Lightest set of edges that touches every vertex. C: covered from below, N: not yet."""
    return Problem(
        "minimum_edge_cover",
        ("C", "N"),
        {"N": 0},
        (("C", "N", 0), ("C", "C", EDGE), ("N", "C", EDGE)),
        (("N", "N", "N"), ("C", "N", "C"), ("N", "C", "C"), ("C", "C", "C")),
        ("C",),
        sense="min",
        unit=unit,
    )


def longest_path(unit: bool = False) -> Problem:
    """Heaviest path. Z: nothing chosen, P: a path that ends here, D: a path below, closed."""
    return Problem(
        "longest_path",
        ("Z", "P", "D"),
        {"Z": 0},
        (("Z", "Z", 0), ("Z", "P", EDGE), ("P", "P", EDGE), ("P", "D", 0), ("D", "D", 0)),
        (("Z", "Z", "Z"), ("Z", "P", "P"), ("P", "Z", "P"), ("P", "P", "D"), ("Z", "D", "D"), ("D", "Z", "D")),
        ("Z", "P", "D"),
        unit=unit,
    )


def height() -> Problem:
    """Edges on the longest way down. Z: this vertex ends the way, P: the way goes on below."""
    return Problem("height", ("Z", "P"), {"Z": 0}, (("Z", "P", EDGE), ("P", "P", EDGE), ("Z", "Z", 0)), (("Z", "Z", "Z"), ("Z", "P", "P"), ("P", "Z", "P")), ("Z", "P"), unit=True)


def subtree_sum(unit: bool = False) -> Problem:
    """Sum of weights below and at a vertex; with unit weights its size."""
    return Problem("subtree_size" if unit else "subtree_sum", ("S",), {"S": NODE}, (("S", "S", 0),), (("S", "S", "S"),), ("S",), unit=unit)


def colouring(c: int) -> Problem:
    """Cheapest proper colouring with c colours, where colour i at a vertex costs i times its weight (i from 0)."""
    names = tuple(f"c{i}" for i in range(c))
    lift = tuple((a, b, 0) for a in names for b in names if a != b)
    return Problem(f"colouring_{c}", names, {s: (NODE, i) for i, s in enumerate(names)}, lift, tuple((s, s, s) for s in names), names, sense="min", init_helper={s: 0 for s in names})


def r_hop_domination(r: int, unit: bool = True) -> Problem:
    """Fewest centres so that every vertex is within r edges of one.

    States a0..ar: nearest centre below is i edges away, all served; b0..br-1 and so on: the
    farthest unserved vertex below is i edges away. A served vertex may still need nothing.
    """
    a = [f"a{i}" for i in range(r + 1)]
    b = [f"b{i}" for i in range(r + 1)]
    lift = [(a[i], a[i + 1], 0) for i in range(r)] + [(b[i], b[i + 1], 0) for i in range(r)] + [(a[r], "z", 0), ("z", "z", 0)]
    states = (*a, *b, "z")
    join = []
    for i in range(r + 1):
        for j in range(r + 1):
            join.append((a[i], a[j], a[min(i, j)]))
            join.append((b[i], b[j], b[max(i, j)]))
            served = a[i] if i + j <= r else b[j]
            join += [(a[i], b[j], served), (b[j], a[i], served)]
        join += [(a[i], "z", a[i]), ("z", a[i], a[i]), (b[i], "z", b[i]), ("z", b[i], b[i])]
    join.append(("z", "z", "z"))
    return Problem(f"domination_{r}_hops", states, {"a0": NODE, "b0": 0}, tuple(lift), tuple(join), (*a, "z"), sense="min", init_helper={"z": 0}, unit=unit)


PROBLEMS = {
    "mwm": matching,
    "mcm": lambda: matching(unit=True),
    "mvc": vertex_cover,
    "mis": independent_set,
    "mds": dominating_set,
    "mids": independent_dominating_set,
    "mec": edge_cover,
    "lpath": longest_path,
    "height": height,
    "subtree_sum": subtree_sum,
    "subtree_size": lambda: subtree_sum(unit=True),
}
