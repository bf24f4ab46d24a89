"""Kernels over one world or one sketch, for Python workers.

Graphs are the plain arrays of ``planner.adjacency``; node numbers are places
in its ``nodes``. They hold edges, or rows of actions from which a node's edges
are found (``sources.meetings``).
"""

from __future__ import annotations

import numpy as np

from nudgegraph.functions.coins import SPAN, coin_array
from nudgegraph.model import SUPER


def _fan(ptr: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edge places of the rows, and for each the row it belongs to."""
    size = ptr[rows + 1] - ptr[rows]
    owner = np.repeat(rows, size)
    start = np.repeat(ptr[rows] - np.concatenate([[0], np.cumsum(size)[:-1]]), size)
    return start + np.arange(size.sum()), owner


def met(g: dict, way: str, rows: np.ndarray, open_=None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(others, owners, hits): whom the rows meet in a graph of actions and how often, in the order of owners and others."""
    at, who = _fan(g["row_ptr"], rows)
    lo = g[f"{way}_lo"][at].astype(np.int64)
    size = g[f"{way}_hi"][at] - lo
    owner = np.repeat(who, size)
    to = g["place"][np.repeat(lo - (np.cumsum(size) - size), size) + np.arange(len(owner))]
    if open_ is not None:
        good = open_(to)
        to, owner = to[good], owner[good]
    key = np.sort(owner.astype(np.int64) * len(g["nodes"]) + to)
    first = np.flatnonzero(np.diff(key, prepend=-1))
    return key[first] % len(g["nodes"]), key[first] // len(g["nodes"]), np.diff(first, append=len(key))


def chances(g: dict, src: np.ndarray, hits: np.ndarray | int) -> tuple[np.ndarray, np.ndarray]:
    """(p, q) of edges in a graph of actions: as ``learn_probabilities`` learns them and ``with_boost`` raises them."""
    p, beta = np.minimum(1.0, g["scale"] * hits / g["done"][src]), g.get("beta", 2.0)
    miss = 1 - p
    if not (float(beta).is_integer() and 1 <= beta <= 16):
        return p, 1 - np.power(miss, beta)
    left = miss
    for _ in range(int(beta) - 1):
        left = left * miss
    return p, 1 - left


def _thresholds(g: dict, src: np.ndarray, hits: np.ndarray | int) -> tuple[np.ndarray, np.ndarray]:
    return tuple(np.floor(x * SPAN).astype(np.int64) for x in chances(g, src, hits))


def fan(g: dict, way: str, rows: np.ndarray, open_=None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(others, owners, thresholds, raised thresholds) of the rows' edges; ``open_`` tells which others matter."""
    if "place" in g:
        to, owner, hits = met(g, way, rows, open_)
        return to, owner, *_thresholds(g, owner if way == "out" else to, hits)
    at, owner = _fan(g[f"{way}_ptr"], rows)
    if open_ is not None:
        good = open_(g[f"{way}_to"][at])
        at, owner = at[good], owner[good]
    return g[f"{way}_to"][at], owner, g[f"{way}_tp"][at], g[f"{way}_tq"][at]


#: edges of a front that are looked at together; a node that they reach isn't tried again by those after them
EDGES_AT_ONCE = 32_768


def parts(front: np.ndarray, ptr: np.ndarray, at_once: int | None = None) -> list[np.ndarray]:
    """The front in parts of about so many edges."""
    if not len(front):
        return []
    size = np.cumsum(ptr[front + 1] - ptr[front])
    return np.split(front, np.flatnonzero(np.diff(size // (at_once or EDGES_AT_ONCE))) + 1)


def _size(ptr: np.ndarray, rows: np.ndarray) -> int:
    return int((ptr[rows + 1] - ptr[rows]).sum())


#: share of all nodes from which on a front is looked for by the nodes that it may reach; how many whom a node's row meets
#: are tried at once, row by row while so large a share of the nodes is found
DENSE, MET_TRIED, LEAST_FOUND = 1 / 16, 32, 0.05


def _reached_by_many(g: dict, way: str, left: np.ndarray, front: np.ndarray, live) -> np.ndarray:
    """The nodes of ``left`` that a live edge joins with the front, in a graph of actions: the same as from the front's side.

    ``way`` leads from ``left`` to the front; ``live`` judges (others, owners,
    thresholds, raised thresholds). An edge is at least as likely as one
    meeting makes it, so nearly all nodes are found by a few meetings; only
    those that aren't have their edges looked at with all meetings counted.
    """
    back, n = {"out": "in", "in": "out"}[way], len(g["nodes"])
    inside = np.zeros(n, bool)
    inside[front] = True
    found = np.zeros(n, bool)
    ask, j, before = left, 0, np.inf
    while len(ask) and len(ask) <= (1 - LEAST_FOUND) * before:
        for some in np.array_split(ask, max(1, len(ask) * MET_TRIED // (8 * EDGES_AT_ONCE))):
            at = g["row_ptr"][some] + j
            lo = g[f"{way}_lo"][at].astype(np.int64)
            size = np.minimum(g[f"{way}_hi"][at] - lo, MET_TRIED)
            owner = np.repeat(some, size)
            to = g["place"][np.repeat(lo - (np.cumsum(size) - size), size) + np.arange(len(owner))]
            good = inside[to]
            to, owner = to[good], owner[good]
            found[owner[live(to, owner, *_thresholds(g, owner if way == "out" else to, 1))]] = True
        j, before = j + 1, len(ask)
        ask = ask[~found[ask] & (g["row_ptr"][ask] + j < g["row_ptr"][ask + 1])]
    left = left[~found[left]]
    if _size(g[f"{way}_ptr"], left) < _size(g[f"{back}_ptr"], front):
        for some in parts(left, g[f"{way}_ptr"]):
            to, owner, tp, tq = fan(g, way, some, lambda to: inside[to])
            found[owner[live(to, owner, tp, tq)]] = True
    else:
        open_ = np.zeros(n, bool)
        open_[left] = True
        for some in parts(front, g[f"{back}_ptr"]):
            to, owner, tp, tq = fan(g, back, some, lambda to: open_[to])
            new = to[live(owner, to, tp, tq)]
            found[new], open_[new] = True, False
    return np.flatnonzero(found)


class Workspace:
    """Arrays over all nodes that a worker uses again and again: a run pays for what it visits, not for n."""

    def __init__(self, n: int):
        self.step = np.full((2, n), -1)
        self.dist = np.full(n, -1)
        self.boosted = np.zeros(n, bool)


def cascade(g: dict, seeds: np.ndarray, boost: np.ndarray, world: int, salt: int, coins: str, mode: str, space: Workspace | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, steps) active in one world.

    ``receiver``: edges into boosted nodes have the raised chance; ``sender``:
    edges out of them; ``single_boost``: an active node is reached over at most
    one edge that is live by its boosted head alone.
    """
    space = Workspace(len(g["nodes"])) if space is None else space
    boosted, layers = space.boosted, 2 if mode == "single_boost" else 1
    boosted[boost] = True
    step_of = space.step
    front = [np.unique(seeds)] + [np.empty(0, np.int64)] * (layers - 1)
    step_of[0, front[0]] = 0
    step, visited = 0, [list(front[:1]), []]
    while any(len(f) for f in front):
        step += 1
        reached = [[] for _ in range(layers)]
        if "place" in g and mode != "single_boost" and len(front[0]) > DENSE * len(g["nodes"]):

            def active(tail, head, tp, tq):
                h = coin_array(coins, salt, world, g["nodes"][tail], g["nodes"][head])
                return h < np.where(boosted[tail if mode == "sender" else head], tq, tp)

            new = _reached_by_many(g, "in", np.flatnonzero(step_of[0] < 0), front[0], active)
            step_of[0, new] = step
            reached[0].append(new)
            front = [front[0][:0]]
        for layer, rows in ((layer, part) for layer, whole in enumerate(front) for part in parts(whole, g["out_ptr"])):
            # coins decide nothing for heads that are active already
            to, owner, tp, tq = fan(g, "out", rows, lambda to, layer=layer: step_of[layer:layers, to].min(0) < 0)
            h = coin_array(coins, salt, world, g["nodes"][owner], g["nodes"][to])
            live, raised = h < tp, h < tq
            if mode == "single_boost":
                reached[layer].append(to[live])
                if layer == 0:
                    reached[1].append(to[~live & raised & boosted[to]])
            else:
                helped = boosted[owner] if mode == "sender" else boosted[to]
                new = to[np.where(helped, raised, live)]
                step_of[0, new] = step
                reached[0].append(new)
        front = []
        for layer in range(layers):
            new = np.unique(np.concatenate(reached[layer])) if reached[layer] else np.empty(0, np.int64)
            if mode == "single_boost":
                new = new[step_of[layer, new] < 0]
                step_of[layer, new] = step
            front.append(new)
            visited[layer].append(new)
    nodes = np.unique(np.concatenate([*visited[0], *visited[1]]))
    steps = step_of[:layers, nodes]
    first = np.where(steps < 0, np.iinfo(np.int64).max, steps).min(0)
    step_of[:, nodes] = -1
    boosted[boost] = False
    return nodes, first


def helped(g: dict, active: np.ndarray, boost: np.ndarray, world: int, salt: int, coins: str, space: Workspace) -> int:
    """How many more nodes turn active in a world if the set is boosted, given the mask of those that do anyway.

    Edges are raised for boosted receivers alone, so whatever is new starts at
    one of them that an active node reaches; nothing else is looked at again.
    """
    ask = boost[~active[boost]]
    if not len(ask):
        return 0
    boosted, mine = space.boosted, active.copy()
    boosted[boost] = True

    def judged(tail, head, tp, tq):
        return coin_array(coins, salt, world, g["nodes"][tail], g["nodes"][head]) < np.where(boosted[head], tq, tp)

    reached = []
    for rows in parts(ask, g["in_ptr"]):
        tail, head, tp, tq = fan(g, "in", rows, lambda to: active[to])
        reached.append(head[judged(tail, head, tp, tq)])
    front = np.unique(np.concatenate(reached))
    mine[front] = True
    found = len(front)
    while len(front):
        reached = []
        for rows in parts(front, g["out_ptr"]):
            head, tail, tp, tq = fan(g, "out", rows, lambda to: ~mine[to])
            reached.append(np.unique(head[judged(tail, head, tp, tq)]))
            mine[reached[-1]] = True
        front = np.concatenate(reached)
        found += len(front)
    boosted[boost] = False
    return found


def reach_set(g: dict, root: int, world: int, salt: int, coins: str, space: Workspace | None = None) -> np.ndarray:
    """Nodes from which live edges lead to the root."""
    seen = (Workspace(len(g["nodes"])) if space is None else space).boosted
    seen[root] = True
    front = np.array([root])
    found = [front]
    while len(front):
        reached = []
        if "place" in g and len(front) > DENSE * len(g["nodes"]):
            live = lambda head, tail, tp, tq: coin_array(coins, salt, world, g["nodes"][tail], g["nodes"][head]) < tp
            reached.append(_reached_by_many(g, "out", np.flatnonzero(~seen), front, live))
            seen[reached[-1]] = True
            front = front[:0]
        for rows in parts(front, g["in_ptr"]):
            # coins decide nothing for tails that are found already
            tail, owner, tp, _ = fan(g, "in", rows, lambda to: ~seen[to])
            live = coin_array(coins, salt, world, g["nodes"][tail], g["nodes"][owner]) < tp
            reached.append(np.unique(tail[live]))
            seen[reached[-1]] = True
        front = np.concatenate(reached)
        found.append(front)
    nodes = np.sort(np.concatenate(found))
    seen[nodes] = False
    return nodes


def grow(g: dict, is_seed: np.ndarray, root: int, world: int, salt: int, coins: str, cap: int, space: Workspace | None = None) -> tuple[str, list[tuple[int, int, bool]], int, dict[int, int]]:
    """(category, raw edges, edges touched, distance of each node to the root).

    Layer by layer in the number of edges that need a boost: all live edges at
    one distance first, then one step over the others. Seeds aren't expanded;
    an edge whose tail would lie beyond the cap isn't kept. A live edge from a
    seed at distance zero ends the search there and then. Other nodes of
    distance zero keep just one live edge, to the root itself.
    """
    if is_seed[root]:
        return "activated", [], 0, {root: 0}
    dist = (Workspace(len(g["nodes"])) if space is None else space).dist
    later: list[np.ndarray] = []
    tails, heads, lives = [], [], []
    touched, d, seen_seed = 0, 0, False
    dist[root] = 0
    open_ = np.array([root])
    visited = [open_]
    try:
        while len(open_):
            while len(open_):
                before, open_ = open_, []
                for rows in parts(before, g["in_ptr"]):
                    tail, head, tp, tq = fan(g, "in", rows)
                    h = coin_array(coins, salt, world, g["nodes"][tail], g["nodes"][head])
                    live = h < tp
                    if d == 0:
                        ends = np.flatnonzero(live & is_seed[tail])
                        if len(ends):
                            return "activated", [], touched + int(ends[0]) + 1, {}
                    touched += len(tail)
                    lub = ~live & (h < tq) & (d + 1 <= cap)
                    keep = live | lub
                    tails.append(tail[keep])
                    heads.append(head[keep])
                    lives.append(live[keep])
                    later.append(tail[lub])
                    new = np.unique(tail[live])
                    new = new[dist[new] < 0]
                    dist[new] = d
                    visited.append(new)
                    seen_seed |= bool(is_seed[new].any())
                    open_.append(new[~is_seed[new]])
                open_ = np.sort(np.concatenate(open_))
            new = np.unique(np.concatenate(later)) if later else np.empty(0, np.int64)
            later = []
            new = new[dist[new] < 0]
            d += 1
            dist[new] = d
            visited.append(new)
            seen_seed |= bool(is_seed[new].any())
            open_ = new[~is_seed[new]]
        if not seen_seed:
            return "hopeless", [], touched, {}
        u, v, live = np.concatenate(tails), np.concatenate(heads), np.concatenate(lives)
        far = dist[u] > 0
        raw = list(zip(u[far].tolist(), v[far].tolist(), live[far].tolist(), strict=True))
        nodes = np.concatenate(visited)
        raw += [(x, int(root), True) for x in nodes[(dist[nodes] == 0) & (nodes != root)].tolist()]
        return "boostable", raw, touched, dict(zip(nodes.tolist(), dist[nodes].tolist(), strict=True))
    finally:
        for nodes in visited:
            dist[nodes] = -1


def _distances(starts: list[int], step: dict[int, list[tuple[int, bool]]], barred: set[int] = frozenset()) -> dict[int, int]:
    """Least number of not-live edges from the starts."""
    dist = {s: 0 for s in starts}
    now, d = list(starts), 0
    while now:
        later = []
        while now:
            v = now.pop()
            if dist[v] != d:
                continue
            for w, live in step.get(v, ()):
                if w in barred:
                    continue
                if live:
                    if dist.get(w, d + 1) > d:
                        dist[w] = d
                        now.append(w)
                elif dist.get(w, d + 2) > d + 1:
                    dist[w] = d + 1
                    later.append(w)
        now, d = later, d + 1
    return dist


def _maps(edges) -> tuple[dict, dict]:
    ahead: dict[int, list] = {}
    back: dict[int, list] = {}
    for u, v, live in edges:
        ahead.setdefault(u, []).append((v, live))
        back.setdefault(v, []).append((u, live))
    return ahead, back


def compress(root: int, raw: list[tuple[int, int, bool]], seeds: set[int], cap: int) -> tuple[list[tuple[int, int, bool]], list[int]]:
    """(edges, critical nodes) of a boostable sketch, equivalent for any boost set of at most ``cap`` nodes.

    Nodes that seeds reach by live edges become one. A node is dropped where
    its distances to both ends exceed the cap; one that reaches the root by
    live edges keeps only a live edge to it.
    """
    # nodes of distance zero lead to the root anyway: their other ways are redundant
    ahead, back = _maps(raw)
    from_seeds = _distances([v for v in seeds if v in ahead], ahead)
    merged = {v for v, d in from_seeds.items() if d == 0}
    to_root = _distances([root], back, merged)
    critical = sorted({v for u, v, live in raw if not live and u in merged and v not in merged and to_root.get(v) == 0})
    near = {v for v, d in to_root.items() if v not in merged and d + from_seeds.get(v, cap + 1) <= cap}
    out: set[tuple[int, int, bool]] = set()
    for u, v, live in raw:
        if v not in near:
            continue
        if u in merged:
            out.add((SUPER, v, live))
        elif u in near and (to_root[u] > 0):
            out.add((u, v, live))
    out |= {(v, root, True) for v in near if v != root and to_root[v] == 0}
    # only what lies on a way from the merged seeds to the root stays
    while True:
        ahead, back = _maps(out)
        good = set(_distances([SUPER], ahead)) & set(_distances([root], back))
        left = {e for e in out if e[0] in good and e[1] in good}
        if left == out:
            break
        out = left
    return sorted(out), critical


def activates(root: int, edges, boost: set[int]) -> bool:
    """Does boosting the set activate the root?"""
    seen, now = {SUPER}, [SUPER]
    ahead: dict[int, list[int]] = {}
    for u, v, live in edges:
        if live or v in boost:
            ahead.setdefault(u, []).append(v)
    while now:
        for w in ahead.get(now.pop(), ()):
            if w == root:
                return True
            if w not in seen:
                seen.add(w)
                now.append(w)
    return False


def marginal_nodes(root: int, edges, boost: set[int]) -> list[int]:
    """Nodes that, boosted besides the set, activate a root that isn't active yet."""
    passable = [(u, v) for u, v, live in edges if live or v in boost]
    ahead, back = _maps((u, v, True) for u, v in passable)
    front = set(_distances([SUPER], ahead))
    if root in front:
        return []
    rear = set(_distances([root], back))
    return sorted({v for u, v, live in edges if not live and v not in boost and u in front and v in rear})
