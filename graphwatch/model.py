"""Patterns, pieces and join trees: small objects on the driver."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

EDGE_COLUMNS = ["eid", "src", "dst", "etype", "ts"]
#: The kind of a query edge that any edge fits; its predicate may tell more, such as etype rlike '^k[45]$'.
ANY = "*"


@dataclass(frozen=True)
class QueryVertex:
    name: str
    vtype: str | None = None  # looked up in a table of vertices, as label is
    predicate: str | None = None  # SQL over vid
    label: str | None = None  # regular expression


@dataclass(frozen=True)
class QueryEdge:
    name: str
    src: str
    dst: str
    etype: str
    predicate: str | None = None  # SQL over the edge's columns

    @property
    def ends(self) -> tuple[str, str]:
        return self.src, self.dst


@dataclass(frozen=True)
class QueryGraph:
    edges: tuple[QueryEdge, ...]
    vertices: tuple[QueryVertex, ...] = ()

    @property
    def vertex_names(self) -> list[str]:
        return list(dict.fromkeys(v for e in self.edges for v in e.ends))

    def predicate(self, vertex: str) -> str | None:
        return next((v.predicate for v in self.vertices if v.name == vertex), None)

    def vertex(self, name: str) -> QueryVertex | None:
        return next((v for v in self.vertices if v.name == name), None)

    def connected(self) -> bool:
        seen, todo = set(), {self.edges[0].src} if self.edges else set()
        while todo:
            v = todo.pop()
            seen.add(v)
            todo |= {u for e in self.edges if v in e.ends for u in e.ends} - seen
        return seen == set(self.vertex_names)


def pattern(*edges: str, **predicates: str) -> QueryGraph:
    """pattern("a -k4> b", "b -k0> c", a="vid < 10"): edges are named e0, e1, ..."""
    made = []
    for i, text in enumerate(edges):
        src, kind, dst = text.replace(" -", " ").replace("> ", " ").split()
        made.append(QueryEdge(f"e{i}", src, dst, kind))
    return QueryGraph(tuple(made), tuple(QueryVertex(k, predicate=v) for k, v in predicates.items()))


@dataclass(frozen=True)
class Leaf:
    """A piece of one or two edges."""

    edges: tuple[QueryEdge, ...]

    @property
    def vertices(self) -> list[str]:
        return list(dict.fromkeys(v for e in self.edges for v in e.ends))

    @property
    def centre(self) -> str | None:
        """The vertex at which the two edges meet."""
        if len(self.edges) < 2:
            return None
        return next(v for v in self.edges[0].ends if v in self.edges[1].ends)


@dataclass(frozen=True)
class JoinTree:
    """Left-deep: leaf 0, then each leaf joined to the prefix before it."""

    leaves: tuple[Leaf, ...]
    fallback: bool = False  # an unseen pair made single edges of what could be a pair
    notes: tuple[str, ...] = field(default=())

    def prefix_vertices(self, i: int) -> list[str]:
        """Vertices of leaves 0 to i."""
        return list(dict.fromkeys(v for leaf in self.leaves[: i + 1] for v in leaf.vertices))

    def cut(self, i: int) -> list[str]:
        """Vertices that leaf i shares with the prefix before it."""
        before = set(self.prefix_vertices(i - 1))
        return [v for v in self.leaves[i].vertices if v in before]

    @property
    def edges(self) -> list[QueryEdge]:
        return [e for leaf in self.leaves for e in leaf.edges]


def tree_json(tree: JoinTree, graph: QueryGraph) -> str:
    return json.dumps({
        "leaves": [[[e.name, e.src, e.dst, e.etype, e.predicate] for e in leaf.edges] for leaf in tree.leaves],
        "fallback": tree.fallback,
        "vertices": [[v.name, v.vtype, v.predicate, v.label] for v in graph.vertices],
    })


def tree_from_json(text: str) -> tuple[JoinTree, QueryGraph]:
    made = json.loads(text)
    leaves = tuple(Leaf(tuple(QueryEdge(*e) for e in leaf)) for leaf in made["leaves"])
    edges = tuple(sorted((e for leaf in leaves for e in leaf.edges), key=lambda e: e.name))
    return JoinTree(leaves, made["fallback"]), QueryGraph(edges, tuple(QueryVertex(*v) for v in made["vertices"]))
