"""Tree patterns as preorder codes.

A code lists ``label@depth`` in preorder, joined by spaces. Equal codes are equal
(isomorphic) ordered trees. A rightmost extension appends one token.
"""

from __future__ import annotations

from itertools import product

Nodes = tuple[tuple[str, int], ...]

_ESCAPES = (("%", "%25"), (" ", "%20"), ("@", "%40"))


def escape(label: str) -> str:
    for raw, safe in _ESCAPES:
        label = label.replace(raw, safe)
    return label


def unescape(label: str) -> str:
    for raw, safe in reversed(_ESCAPES):
        label = label.replace(safe, raw)
    return label


def parse(code: str) -> Nodes:
    """(escaped label, depth) in preorder. Raises ValueError for what isn't one tree."""
    nodes = tuple((label, int(depth)) for label, depth in (token.rsplit("@", 1) for token in code.split(" ")))
    depths = [d for _, d in nodes]
    if not nodes or depths[0] != 0 or any(not 1 <= b <= a + 1 for a, b in zip(depths, depths[1:])):
        raise ValueError(f"not a tree pattern: {code}")
    return nodes


def code(nodes: Nodes) -> str:
    return " ".join(f"{label}@{depth}" for label, depth in nodes)


def attach_depths(nodes: Nodes) -> list[int]:
    """For each vertex after the root, the depth of the rightmost-path vertex that it is attached to."""
    return [d - 1 for _, d in nodes[1:]]


def rightmost_path(nodes: Nodes) -> list[int]:
    """Places in preorder of the vertices from the root to the last vertex."""
    out: list[int] = []
    for i, (_, d) in enumerate(nodes):
        out = [*out[:d], i]
    return out


def extend(nodes: Nodes, label: str, c: int) -> Nodes:
    """A new last child under the rightmost-path vertex at depth c."""
    if not 0 <= c <= nodes[-1][1]:
        raise ValueError(f"no rightmost-path vertex at depth {c}")
    return (*nodes, (label, c + 1))


def extensions(nodes: Nodes, labels: list[str]) -> list[Nodes]:
    """All rightmost extensions by the given labels."""
    return [extend(nodes, label, c) for label, c in product(labels, range(nodes[-1][1] + 1))]


def is_isomorphic(a: str, b: str) -> bool:
    return parse(a) == parse(b)


def class_partner(nodes: Nodes, label: str, c: int) -> Nodes | None:
    """The sibling that must be frequent too for an extension to be made: the prefix with the new vertex in the last one's place, no deeper."""
    if len(nodes) == 1:
        return None
    return (*nodes[:-1], (label, min(c, nodes[-1][1] - 1) + 1))


def one_removed(nodes: Nodes) -> list[Nodes]:
    """Patterns with one vertex less: its children move up to its parent; the root can go only if it has one child."""
    out = []
    for i, (_, d) in enumerate(nodes):
        end = next((j for j in range(i + 1, len(nodes)) if nodes[j][1] <= d), len(nodes))
        if i == 0 and sum(x == 1 for _, x in nodes) != 1:
            continue
        out.append(nodes[:i] + tuple((label, x - 1) for label, x in nodes[i + 1 : end]) + nodes[end:])
    return list(dict.fromkeys(n for n in out if n))
