"""Hypergraph, join tree, attribute splits and roles; plain Python over a handful of relations."""

from __future__ import annotations

from dataclasses import dataclass, field

from multiagg.plans.spec import GroupedJoinSpec, SpecError


@dataclass(frozen=True)
class Hypergraph:
    """Relevant attributes as vertices; each relation is the set of its own."""

    edges: dict[str, frozenset[str]]
    groups: dict[str, tuple[str, ...]]

    @property
    def vertices(self) -> set[str]:
        return set().union(*self.edges.values()) if self.edges else set()


def build_hypergraph(spec: GroupedJoinSpec) -> Hypergraph:
    return Hypergraph({r.name: frozenset(r.attrs) for r in spec.relations}, {r.name: r.group for r in spec.relations})


def is_acyclic(h: Hypergraph) -> bool:
    """Ears go first: a relation whose shared attributes all lie in one other relation can be taken away."""
    left = dict(h.edges)
    while len(left) > 1:
        for name, attrs in left.items():
            others = {n: a for n, a in left.items() if n != name}
            shared = attrs & frozenset().union(*others.values())
            if any(shared <= a for a in others.values()):
                del left[name]
                break
        else:
            return False
    return True


@dataclass
class Node:
    name: str
    up: tuple[str, ...]
    group: tuple[str, ...]
    children: list[Node] = field(default_factory=list)
    #: Names of the children in the order in which they are met, where one has been chosen.
    order: list[str] = field(default_factory=list)

    @property
    def down(self) -> tuple[str, ...]:
        return tuple(sorted({a for c in self.children for a in c.up}))

    def walk(self):
        yield self
        for c in self.children:
            yield from c.walk()


def decompose(h: Hypergraph, root: str | None = None) -> Node:
    """A join tree: a spanning tree of greatest overlap, turned so that `root` is on top.

    Greatest overlap makes the relations of each attribute hang together, which is asserted.
    """
    if not is_acyclic(h):
        raise SpecError("the join is cyclic")
    names = list(h.edges)
    root = root or next((n for n in names if h.groups[n]), names[0])
    inside, links = {root}, {}
    while len(inside) < len(names):
        size, a, b = max(((len(h.edges[a] & h.edges[b]), a, b) for a in names if a in inside for b in names if b not in inside), key=lambda x: (x[0], -names.index(x[1]), -names.index(x[2])))
        if not size:
            raise SpecError(f"nothing joins {b} to the rest")
        links.setdefault(a, []).append(b)
        inside.add(b)

    def grow(name: str, parent: str | None) -> Node:
        up = tuple(sorted(h.edges[name] & h.edges[parent])) if parent else ()
        return Node(name, up, h.groups[name], [grow(c, name) for c in links.get(name, [])])

    tree = grow(root, None)
    _check_running_intersection(h, tree)
    return tree


def _check_running_intersection(h: Hypergraph, tree: Node) -> None:
    for attr in h.vertices:
        tops = [n for n in tree.walk() if attr in h.edges[n.name] and attr not in n.up]
        if len(tops) > 1:
            raise SpecError(f"the relations of {attr} do not hang together in the tree")


def split_attributes(tree: Node) -> dict[str, tuple[tuple[str, ...], tuple[str, ...]]]:
    """Left and right attributes of each relation: the root leads from its group to its children, an inner one from parent to children, one with a group (not the root) from all else to its group."""
    out = {}
    for n in tree.walk():
        if n is tree:
            out[n.name] = (n.group, n.down)
        elif n.group:
            out[n.name] = (tuple(sorted({*n.up, *n.down})), n.group)
        else:
            out[n.name] = (n.up, n.down)
    return out


def classify(tree: Node) -> dict[str, set[str]]:
    """Roles of each relation; they overlap."""
    out = {}
    for n in tree.walk():
        roles = set()
        if n is tree:
            roles.add("source")
        if len(n.children) > 1 or (n is not tree and n.group and n.children):
            roles.add("branch")
        if n.group and n is not tree:
            roles.add("group")
        if n is not tree and not n.group:
            roles.add("inner")
        out[n.name] = roles
    return out


def drawn(tree: Node, depth: int = 0) -> list[str]:
    here = f"{'  ' * depth}{tree.name}" + (f" on ({', '.join(tree.up)})" if tree.up else "") + (f" gives ({', '.join(tree.group)})" if tree.group else "")
    return [here, *(line for c in tree.children for line in drawn(c, depth + 1))]
