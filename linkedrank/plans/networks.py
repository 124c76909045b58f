"""Networks: tree-shaped join templates over matched and free sets, built on the driver."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property
from itertools import permutations

from linkedrank.plans.catalog import LinkedSchema


@dataclass(frozen=True)
class Network:
    """nodes: (relation, matched?); edges: (child node, parent node, link name)."""

    nodes: tuple[tuple[str, bool], ...]
    edges: tuple[tuple[int, int, str], ...]

    @property
    def size(self) -> int:
        return len(self.nodes)

    def adjacent(self, i: int) -> list[tuple[int, str]]:
        """(other node, label); the label tells the link and which end is the child."""
        out = [(p, f"{link}^") for c, p, link in self.edges if c == i]
        return out + [(c, f"{link}v") for c, p, link in self.edges if p == i]

    def leaves(self) -> list[int]:
        return [i for i in range(self.size) if len(self.adjacent(i)) <= 1]

    def rooted(self, i: int, parent: int = -1) -> tuple[str, tuple[int, ...]]:
        """Code and canonical node order of the subtree of i seen from parent."""
        rel, matched = self.nodes[i]
        parts = sorted((label + c, order) for j, label in self.adjacent(i) if j != parent for c, order in [self.rooted(j, i)])
        return f"{rel}{'+' if matched else '0'}({','.join(c for c, _ in parts)})", (i, *(k for _, o in parts for k in o))

    def center(self) -> int:
        """Node of least eccentricity (ties: smaller code): depth is at most size // 2 + 1 nodes."""

        def far(i, parent):
            return 1 + max((far(j, i) for j, _ in self.adjacent(i) if j != parent), default=0)

        return min(range(self.size), key=lambda i: (far(i, -1), self.rooted(i)[0]))

    @cached_property
    def code(self) -> str:
        return min(self.rooted(i)[0] for i in range(self.size))

    def canonical(self) -> Network:
        """The same network with nodes in canonical order."""
        order = min(self.rooted(i) for i in range(self.size))[1]
        at = {old: new for new, old in enumerate(order)}
        return Network(tuple(self.nodes[i] for i in order), tuple(sorted((at[c], at[p], link) for c, p, link in self.edges)))

    @cached_property
    def automorphisms(self) -> list[tuple[int, ...]]:
        """Permutations of nodes that keep nodes and edges, without the identity."""
        edges, same, out = set(self.edges), {}, []
        for i, n in enumerate(self.nodes):
            same.setdefault(n, []).append(i)
        groups = list(same.values())

        def go(g, image):
            if g == len(groups):
                if any(k != v for k, v in image.items()) and {(image[c], image[p], link) for c, p, link in self.edges} == edges:
                    out.append(tuple(image[i] for i in range(self.size)))
                return
            for perm in permutations(groups[g]):
                go(g + 1, image | dict(zip(groups[g], perm)))

        go(0, {})
        return out


def leaves_matched(net: Network) -> bool:
    return all(net.nodes[i][1] for i in net.leaves())


def respects_links(net: Network) -> bool:
    """A child row has one parent per link, so a child node uses a link once at most."""
    used = [(c, link) for c, _, link in net.edges]
    return len(used) == len(set(used))


def generate(schema: LinkedSchema, matched: set[str] | list[str], max_size: int) -> list[Network]:
    """All networks of at most max_size nodes whose leaves are matched, each once."""
    matched, seen, done = set(matched), {}, {}
    wave = [Network(((r, True),), ()) for r in sorted(matched)]
    while wave:
        nxt = []
        for net in wave:
            if net.code in seen:
                continue
            seen[net.code] = True
            if leaves_matched(net):
                done[net.code] = net.canonical()
            if net.size == max_size:
                continue
            for i, (rel, _) in enumerate(net.nodes):
                for link, other, is_child in schema.neighbours(rel):
                    for m in (True, False) if other in matched else (False,):
                        new = net.size
                        edge = (i, new, link.name) if is_child else (new, i, link.name)
                        grown = Network((*net.nodes, (other, m)), (*net.edges, edge))
                        free = sum(not grown.nodes[k][1] for k in grown.leaves())
                        if respects_links(grown) and grown.size + free <= max_size:
                            nxt.append(grown)
        wave = nxt
    return sorted(done.values(), key=lambda n: (n.size, n.code))


def to_sql(net: Network, where: dict[int, str] | None = None, prefix: tuple[str, str] = ("m_", "f_")) -> str:
    """Join text over views m_<relation> (key, links, row_score) and f_<relation> (key, links).

    Rows are distinct members; of symmetric copies the one with the least key text stays.
    """
    a = [f"n{i}" for i in range(net.size)]
    name = [f"{prefix[0] if m else prefix[1]}{rel} {x}" for (rel, m), x in zip(net.nodes, a)]
    text, placed = name[0], {0}
    while len(placed) < net.size:
        c, p, link = next(e for e in net.edges if (e[0] in placed) != (e[1] in placed))
        new = p if c in placed else c
        text += f" JOIN {name[new]} ON {a[c]}.{link} = {a[p]}.key"
        placed.add(new)
    conds = [f"{a[i]}.key <> {a[j]}.key" for i in range(net.size) for j in range(i) if net.nodes[i][0] == net.nodes[j][0]]
    tree = tree_key_sql(net, range(net.size))
    conds += [f"{tree} <= {tree_key_sql(net, perm)}" for perm in net.automorphisms]
    total = " + ".join(f"{x}.row_score" for x, (_, m) in zip(a, net.nodes) if m)
    return (f"SELECT '{net.code}' AS network, {net.size} AS size, {tree} AS tree_key, ({total}) / {net.size} AS score FROM {text}"
            + (" WHERE " + " AND ".join(conds) if conds else ""))


def tree_key_sql(net: Network, order) -> str:
    return " || '>' || ".join(f"'{net.nodes[i][0]}:' || CAST(n{i}.key AS STRING)" for i in order)
