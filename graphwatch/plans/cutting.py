"""Cutting a pattern into pieces, rarest first, and choosing a strategy. All objects are pattern-sized."""

from __future__ import annotations

import itertools
import math
import random
from dataclasses import dataclass, field

from graphwatch.functions.storage import passing_shuffles
from graphwatch.model import ANY, JoinTree, Leaf, QueryEdge, QueryGraph, tree_from_json, tree_json
from graphwatch.operators import stats

THRESHOLD = 1e-3


def pair_signature(one: QueryEdge, two: QueryEdge, centre: str) -> tuple[str, str]:
    a, b = (("o:" if e.src == centre else "i:") + e.etype for e in (one, two))
    return (a, b) if a <= b else (b, a)


@dataclass
class Statistics:
    """Frequencies of kinds and of typed two-edge paths, from a prefix of the stream."""

    kinds: dict[str, int]
    pairs: dict[tuple[str, str], int] = field(default_factory=dict)

    @property
    def edges(self) -> int:
        return sum(self.kinds.values())

    @property
    def paths(self) -> int:
        return sum(self.pairs.values())

    def frequency(self, leaf: Leaf) -> int:
        if len(leaf.edges) == 1:
            return self.kinds.get(leaf.edges[0].etype, 0)
        return self.pairs.get(pair_signature(*leaf.edges, leaf.centre), 0)

    def log10_selectivity(self, leaf: Leaf) -> float | None:
        """None for a piece that the prefix does not have."""
        f, total = self.frequency(leaf), self.edges if len(leaf.edges) == 1 else self.paths
        return math.log10(f / total) if f and total else None


def collect_statistics(edges, prefix: int | None = None, mode: str = "printed") -> Statistics:
    """One row for each kind and pair of kinds comes to the driver."""
    part = stats.sample_prefix(edges, prefix) if prefix else edges
    with passing_shuffles(edges.sparkSession):
        kinds = {r.etype: r.freq for r in stats.edge_histogram(part).collect()}
        pairs = {(r.sig1, r.sig2): r.cnt for r in stats.two_edge_paths(part, mode).collect()}
    return Statistics(kinds, pairs)


def _candidates(left: list[QueryEdge], size: str, known: Statistics) -> list[tuple[tuple, Leaf]]:
    """Pieces within the edges that are left, with their place in the order: rarest, then by signature and edge."""
    index = {e: i for i, e in enumerate(left)}
    singles = [(known.kinds.get(e.etype, 0) / max(known.edges, 1), (e.etype,), (index[e],), Leaf((e,))) for e in left]
    pairs = []
    for one, two in itertools.combinations(left, 2):
        shared = [v for v in one.ends if v in two.ends]
        if one.src == one.dst or two.src == two.dst or len(shared) != 1:
            continue
        sig = pair_signature(one, two, shared[0])
        if sig in known.pairs:
            pairs.append((known.pairs[sig] / max(known.paths, 1), sig, (index[one], index[two]), Leaf((one, two))))
    if size == "edge":
        found = singles
    elif size == "pair":
        found = pairs or singles
    else:
        found = pairs + singles
    return [((f, s, i), leaf) for f, s, i, leaf in sorted(found, key=lambda x: x[:3])]


def cut_pattern(graph: QueryGraph, known: Statistics, size: str = "edge", order: str = "greedy", unseen: str = "piecewise", allow_cartesian: bool = False, seed: int = 0) -> JoinTree:
    """Leaves in join order. size: edge, pair (single edges where no pair fits) or mixed; order: greedy, dp, genetic, mst, cover or random.

    The first leaf is the rarest piece, each next one the rarest that touches what is already
    covered. A pair that the statistics lack is no candidate; with unseen="whole" one such pair
    makes the whole cut one of single edges.
    """
    if not graph.edges:
        raise ValueError("a pattern needs an edge")
    if not graph.connected() and not allow_cartesian:
        raise ValueError("the pattern is not connected; allow_cartesian=True joins its parts all with all")
    pairs = [(a, b) for a, b in itertools.combinations(graph.edges, 2) if len(set(a.ends) & set(b.ends)) == 1]
    missing = [p for p in pairs if pair_signature(*p, next(v for v in p[0].ends if v in p[1].ends)) not in known.pairs]
    if size != "edge" and unseen == "whole" and missing:
        return JoinTree(cut_pattern(graph, known, "edge", order, allow_cartesian=allow_cartesian).leaves, fallback=True)
    left, frontier, leaves = list(graph.edges), set(), []
    while left:
        found = _candidates(left, size, known)
        fits = [x for x in found if not frontier or frontier & set(x[1].vertices)]
        if not fits and size == "pair":
            fits = [x for x in _candidates(left, "edge", known) if not frontier or frontier & set(x[1].vertices)]
        leaf = (fits or found)[0][1]
        leaves.append(leaf)
        frontier |= set(leaf.vertices)
        left = [e for e in left if e not in leaf.edges]
    if order != "greedy":
        leaves = _reordered(leaves, known, order, seed)
    return JoinTree(tuple(leaves), fallback=size != "edge" and bool(missing) and all(len(x.edges) == 1 for x in leaves))


def _connected_orders(leaves: list[Leaf]):
    for p in itertools.permutations(leaves):
        seen: set[str] = set()
        for leaf in p:
            if seen and not seen & set(leaf.vertices):
                break
            seen |= set(leaf.vertices)
        else:
            yield list(p)


def _chain(first: Leaf, leaves: list[Leaf], key) -> list[Leaf]:
    """A connected order from ``first`` on, the next one being least by key(leaf, vertices so far)."""
    chain, rest = [first], [x for x in leaves if x is not first]
    while rest:
        seen = {v for x in chain for v in x.vertices}
        near = [x for x in rest if seen & set(x.vertices)] or rest
        chain.append(min(near, key=lambda x: key(x, seen)))
        rest = [x for x in rest if x is not chain[-1]]
    return chain


def _evolved(leaves: list[Leaf], known: Statistics, seed: int, rounds: int = 40, crowd: int = 16) -> list[Leaf]:
    """A genetic search: priorities of the leaves are the genes, the space of the connected order that they give is the fitness."""
    r = random.Random(seed)

    def order(genes: list[float]) -> list[Leaf]:
        rank = dict(zip(map(id, leaves), genes, strict=True))
        return _chain(min(leaves, key=lambda x: rank[id(x)]), leaves, lambda x, _: rank[id(x)])

    def space(genes: list[float]) -> float:
        return tree_space([known.frequency(x) for x in order(genes)])

    people = [[r.random() for _ in leaves] for _ in range(crowd)]
    for _ in range(rounds):
        people = sorted(people, key=space)[: crowd // 2]
        while len(people) < crowd:
            one, two = r.sample(people[: crowd // 2], 2)
            child = [r.choice(x) for x in zip(one, two, strict=True)]
            child[r.randrange(len(child))] = r.random()
            people.append(child)
    return order(min(people, key=space))


def _reordered(leaves: list[Leaf], known: Statistics, order: str, seed: int) -> list[Leaf]:
    """The same leaves in another connected order.

    dp: of least space (exact, up to 8 leaves); genetic: the same measure by a seeded genetic search;
    mst: by lightest next leaf from each start; cover: from the rarest, the leaf that adds most vertices
    for its frequency; random.
    """
    def space(p: list[Leaf]) -> float:
        return tree_space([known.frequency(x) for x in p])

    if len(leaves) < 2 or order in ("dp", "random") and len(leaves) > 8:
        return leaves
    if order == "random":
        return random.Random(seed).choice(list(_connected_orders(leaves)) or [leaves])
    if order == "dp":
        return min(_connected_orders(leaves), key=space, default=leaves)
    if order == "genetic":
        return _evolved(leaves, known, seed)
    if order == "cover":
        return _chain(min(leaves, key=known.frequency), leaves, lambda x, seen: (known.frequency(x) + 1) / max(len(set(x.vertices) - seen), 0.5))
    return min((_chain(x, leaves, lambda y, _: known.frequency(y)) for x in leaves), key=space)


def rarest_piece(graph: QueryGraph, known: Statistics, size: str = "mixed") -> Leaf:
    return _candidates(list(graph.edges), size, known)[0][1]


def expected_selectivity(tree: JoinTree, known: Statistics) -> float | None:
    """log10 of the product over leaves; None if a leaf is unseen."""
    logs = [known.log10_selectivity(leaf) for leaf in tree.leaves]
    return None if None in logs else sum(logs)


def relative_selectivity(tree_k: JoinTree, tree_1: JoinTree, known: Statistics) -> float | None:
    """log10 of the ratio of the two expected selectivities."""
    a, b = expected_selectivity(tree_k, known), expected_selectivity(tree_1, known)
    return None if a is None or b is None else a - b


@dataclass(frozen=True)
class Choice:
    strategy: str
    tree: JoinTree
    log10_xi: float | None


def choose_strategy(graph: QueryGraph, known: Statistics, threshold: float = THRESHOLD, strategy: str = "auto", **settings) -> Choice:
    """gated2 if the relative selectivity of the pair cut lies below the threshold, else gated1; a named strategy is taken as it is."""
    one, two = cut_pattern(graph, known, "edge", **settings), cut_pattern(graph, known, "pair", **settings)
    xi = relative_selectivity(two, one, known)
    if strategy == "auto":
        strategy = "gated2" if xi is not None and 10**xi < threshold and not two.fallback else "gated1"
    return Choice(strategy, two if strategy.endswith("2") else one, xi)


def order_changed(tree: JoinTree, known: Statistics) -> bool:
    """Whether the pieces of a tree no longer ascend in frequency, or one is not seen any more: a reason to cut anew."""
    freqs = [known.frequency(x) for x in tree.leaves]
    return 0 in freqs or freqs[0] != min(freqs)


# Costs.


def search_cost(leaf: Leaf, degrees: dict[str, float]) -> float:
    """Neighbours looked at around one new edge: 1, or the mean degree of the second edge's signature at the centre."""
    if len(leaf.edges) == 1:
        return 1.0
    second = leaf.edges[1]
    return degrees.get(("o:" if second.src == leaf.centre else "i:") + second.etype, 0.0)


def join_cost(n1: float, n2: float) -> tuple[float, float]:
    """(probes, results) of a join over the stream; results by the rarer side."""
    return n1 + n2, min(n1, n2)


def node_work(search1: float, search2: float, n1: float, n2: float, edges: float) -> float:
    return (search1 + search2 + n1 + n2 + min(n1, n2)) / edges


def tree_work(tree: JoinTree, known: Statistics, degrees: dict[str, float]) -> float:
    """Average work for one edge, from the leaves to the root; an inner child adds its own work in place of a search."""
    def leaf_work(x: Leaf) -> float:
        return known.kinds.get(x.edges[0].etype, 0) * search_cost(x, degrees)

    work, freq = leaf_work(tree.leaves[0]), known.frequency(tree.leaves[0])
    for x in tree.leaves[1:]:
        own = known.frequency(x)
        work += leaf_work(x) + freq + own + min(freq, own)
        freq = min(freq, own)
    return work / max(known.edges, 1)


def tree_space(freqs: list[float]) -> float:
    """Stored matches of a left-deep tree: all leaves and all inner nodes but the root."""
    total, prefix = freqs[0], freqs[0]
    for i, f in enumerate(freqs[1:], 1):
        total += f
        prefix = min(prefix, f)
        if i < len(freqs) - 1:
            total += prefix
    return total


def should_split(freq: float, part_freqs: list[float], mean_degree: float, vertices: int, rule: str = "printed") -> bool:
    """Whether a piece is better split; printed asks for a part above the bound, reversed for one below it."""
    bound = freq / (mean_degree * vertices)
    return any(f > bound if rule == "printed" else f < bound for f in part_freqs)


def q_error(estimate: float, actual: float) -> float:
    low, high = sorted((max(estimate, 1.0), max(actual, 1.0)))
    return high / low


# Plans as text.


def save_plan(tree: JoinTree, graph: QueryGraph, path: str) -> None:
    with open(path, "w") as out:
        out.write(tree_json(tree, graph))


def load_plan(path: str) -> tuple[JoinTree, QueryGraph]:
    with open(path) as src:
        return tree_from_json(src.read())


def explain_tree(tree: JoinTree, known: Statistics | None = None) -> str:
    lines = []
    for i, leaf in enumerate(tree.leaves):
        cut = f" at {', '.join(tree.cut(i))}" if i else ""
        freq = f" freq={known.frequency(leaf)}" if known else ""
        lines.append(f"{i}: " + ", ".join(f"{e.src} -{e.etype}> {e.dst}" for e in leaf.edges) + cut + freq)
    return "\n".join(lines)


def to_sql(tree: JoinTree, graph: QueryGraph, view: str = "edges") -> str:
    """The plan as one SQL query over a view of the edges, joined in the plan's order."""
    seen: dict[str, str] = {}
    where, joins = [], []
    for i, e in enumerate(tree.edges):
        rows = view
        for v, c in ((e.src, "src"), (e.dst, "dst")):
            if p := graph.predicate(v):
                rows = f"(SELECT eid, src, dst, etype, ts FROM (SELECT *, {c} AS vid FROM {rows}) WHERE {p})"
        if e.predicate:
            rows = f"(SELECT eid, src, dst, etype, ts FROM {rows} WHERE {e.predicate})"
        on = [] if e.etype == ANY else [f"{e.name}.etype = '{e.etype}'"]
        for v, c in ((e.src, "src"), (e.dst, "dst")):
            here = f"{e.name}.{c}"
            if v in seen:
                on.append(f"{here} = {seen[v]}")
            else:
                on += [f"{here} <> {o}" for o in seen.values()]
                seen[v] = here
        on += [f"{e.name}.eid <> {o.name}.eid" for o in tree.edges[:i] if o.etype == e.etype or ANY in (o.etype, e.etype)]
        if i:
            joins.append(f"JOIN {rows} {e.name} ON {' AND '.join(on)}")
        else:
            joins.append(f"FROM {rows} {e.name}")
            where = on or ["true"]
    columns = [f"{x} AS v_{v}" for v, x in sorted(seen.items())] + [f"{e.name}.eid AS e_{e.name}" for e in tree.edges]
    last = "greatest(" + ", ".join(f"{e.name}.eid" for e in tree.edges) + ")" if len(tree.edges) > 1 else f"{tree.edges[0].name}.eid"
    return f"SELECT {', '.join(columns)}, {last} AS last_eid {' '.join(joins)} WHERE {' AND '.join(where)}"
