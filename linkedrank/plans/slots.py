"""Shared slot graph: equal rooted subtrees of the networks of one family are one slot."""

from __future__ import annotations

from dataclasses import dataclass, field

from linkedrank.plans.networks import Network


@dataclass
class Slot:
    rel: str
    matched: bool
    family: int
    children: list[tuple[str, str]] = field(default_factory=list)  # (slot code, edge label)
    networks: set[str] = field(default_factory=set)
    root_of: set[str] = field(default_factory=set)
    depth: int = 1


def places(net: Network, family: int) -> dict[int, tuple[int, str]]:
    """The slot of each node."""
    out, todo = {}, [(net.center(), -1)]
    while todo:
        i, parent = todo.pop()
        out[i] = (family, net.rooted(i, parent)[0])
        todo += [(j, i) for j, _ in net.adjacent(i) if j != parent]
    return out


def build(networks: list[Network], families: dict[str, int] | None = None) -> dict[tuple[int, str], Slot]:
    """Slots by (family, subtree code); networks are rooted at their centre."""
    graph: dict[tuple[int, str], Slot] = {}
    for net in networks:
        family = families[net.code] if families else 0

        def add(i, parent):
            code = net.rooted(i, parent)[0]
            kids = [(net.rooted(j, i)[0], label, add(j, i)) for j, label in net.adjacent(i) if j != parent]
            slot = graph.setdefault((family, code), Slot(net.nodes[i][0], net.nodes[i][1], family))
            slot.children = slot.children or sorted((c, label) for c, label, _ in kids)
            slot.depth = 1 + max((d for _, _, d in kids), default=0)
            slot.networks.add(net.code)
            return slot.depth

        add(net.center(), -1)
        graph[family, net.rooted(net.center())[0]].root_of.add(net.code)
    return graph
