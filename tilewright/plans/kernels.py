"""Array forms of the layout methods, for one bucket or sample of boxes.

A kernel takes an (n, 4) array of boxes, the region to cut and the payload, and returns tiles
(xmin, ymin, xmax, ymax, planned) that cover the region (tilings) or the boxes (packings).
"""

from __future__ import annotations

import numpy as np

from ..functions.geometry import Box

Tile = tuple[float, float, float, float, int]


class Sorted:
    """Sorted numbers as distinct values and how many are not above each: no number is repeated in memory.

    Counts may be fractions, as quantiles have them.
    """

    def __init__(self, values: np.ndarray, counts: np.ndarray | None = None):
        if counts is None:
            values, counts = np.unique(np.asarray(values, np.float64), return_counts=True)
        self.values, self.upto = values, np.cumsum(counts)

    def __len__(self) -> int:
        return int(round(float(self.upto[-1]))) if len(self.upto) else 0

    def below(self, edge: float) -> float:
        """How many numbers are below edge."""
        at = int(np.searchsorted(self.values, edge))
        return self.upto[at - 1] if at else 0

    def __getitem__(self, rank: float) -> float:
        """The number of a 0-based rank."""
        return float(self.values[min(int(np.searchsorted(self.upto, rank, "right")), len(self.values) - 1)])

    def beyond(self, edge: float) -> float | None:
        """The smallest number above edge."""
        at = int(np.searchsorted(self.values, edge, "right"))
        return float(self.values[at]) if at < len(self.values) else None


def _centres(b: np.ndarray) -> np.ndarray:
    return (b[:, :2] + b[:, 2:]) / 2


class Live:
    """Which of n objects are live, seen in the order of one of their coordinates.

    Counts per block of `STEP` places answer how many live ones are below a value and which is the k-th,
    so a strip costs what it holds and not another look at all objects.
    """

    STEP = 4096

    def __init__(self, values: np.ndarray, ordered: bool = False):
        """ordered: keep the objects' order, too, for passed()."""
        order = np.argsort(values, kind="stable").astype(np.int32)
        self.values, self.order = values[order], order if ordered else None
        self.place = np.empty(len(values), np.int32)
        self.place[order] = np.arange(len(values), dtype=np.int32)
        self.live = np.ones(len(values), bool)
        self.blocks = np.full(len(values) // self.STEP + 1, self.STEP, np.int64)
        self.blocks[-1] = len(values) % self.STEP
        self.seen = 0

    def drop(self, who: np.ndarray) -> None:
        at = self.place[who]
        self.live[at] = False
        self.blocks -= np.bincount(at // self.STEP, minlength=len(self.blocks))

    def before(self, place: int) -> int:
        block = place // self.STEP
        return int(self.blocks[:block].sum()) + int(self.live[block * self.STEP : place].sum())

    def below(self, value: float) -> int:
        return self.before(int(np.searchsorted(self.values, value)))

    def __getitem__(self, rank: int) -> float:
        """The value of the live object of a 0-based rank."""
        upto = np.cumsum(self.blocks)
        block = int(np.searchsorted(upto, rank, "right"))
        inside = rank - (int(upto[block - 1]) if block else 0)
        at = block * self.STEP
        return float(self.values[at + np.flatnonzero(self.live[at : at + self.STEP])[inside]])

    def beyond(self, value: float, n: int) -> float | None:
        """The smallest live value above one; n: how many are live."""
        rank = self.before(int(np.searchsorted(self.values, value, "right")))
        return self[rank] if rank < n else None

    def passed(self, value: float) -> np.ndarray:
        """The live objects below a value; each call's value is no smaller than the last one's."""
        upto = max(self.seen, int(np.searchsorted(self.values, value)))
        at = self.seen + np.flatnonzero(self.live[self.seen : upto])
        self.seen = upto
        return self.order[at]


def next_cut(centres: Live, n: int, edge: float, payload: int) -> float | None:
    """Where a strip that begins at edge ends: the centre after its first `payload` live ones, or else
    the first centre beyond the edge; None if there is none. n: how many are live."""
    if n > payload and centres[payload] > edge:
        return centres[payload]
    return centres.beyond(edge, n)


def peel(b: np.ndarray, region: Box, payload: int, axes: tuple[str, ...] = ("x", "y")) -> list[Tile]:
    """Strips off the remaining region, each along the axis whose cut crosses the fewest live boxes
    (ties go to the first axis), while more than `payload` boxes are live."""
    rows = peel_axes(b[:, :2], b[:, 2:], [region.xmin, region.ymin], [region.xmax, region.ymax], payload, [0 if a == "x" else 1 for a in axes])
    return [(*low, *high, n) for low, high, n in rows]


def peel_axes(near: np.ndarray, far: np.ndarray, low: list[float], high: list[float], payload: int, axes: list[int] | None = None) -> list[tuple[list[float], list[float], int]]:
    """The same for boxes of any number of axes: (low corner, high corner, planned) of each strip.

    near, far: (n, d) lower and upper corners; low, high: the region's; axes: those that may be cut.
    """
    out = []
    low = list(low)
    axes = list(range(near.shape[1])) if axes is None else axes
    begun = (far >= low).all(axis=1)
    if not begun.all():
        near, far = near[begun], far[begun]
    n = len(near)
    begins, centres, ends = [], [], []
    for d in axes:
        begins.append(Live(near[:, d]))
        centres.append(Live((near[:, d] + far[:, d]) / 2))
        ends.append(Live(far[:, d], ordered=True))
    while True:
        best = None
        if n > payload:
            for k, d in enumerate(axes):
                cut = next_cut(centres[k], n, low[d], payload)
                if cut is None or cut >= high[d]:
                    continue
                crossed = begins[k].below(cut) - ends[k].below(cut)
                if best is None or crossed < best[0]:
                    best = (crossed, k, cut)
        if best is None:
            out.append((list(low), list(high), n))
            return out
        _, k, cut = best
        top = list(high)
        top[axes[k]] = cut
        out.append((list(low), top, centres[k].below(cut)))
        low[axes[k]] = cut
        gone = ends[k].passed(cut)
        for seen in (*begins, *centres, *ends):
            seen.drop(gone)
        n -= len(gone)


def strips(b: np.ndarray, region: Box, payload: int, axis: str = "x", count: str = "live") -> list[Tile]:
    d = 0 if axis == "x" else 1
    cuts = strip_cuts(Sorted(_centres(b)[:, d]), Sorted(b[:, d + 2]), payload, count)
    return tiles_of_cuts(region, [c for c in cuts if region.low(axis) < c < region.high(axis)], axis)


def strip_cuts(centres: Sorted, far: Sorted, payload: int, count: str = "live", min_fresh: int = 0, edge: float = -np.inf) -> list[float]:
    """Cuts from centres and far edges.

    live: boxes that reach over a strip's beginning count for it; fresh: only centres in it do.
    min_fresh: a strip takes in at least so many centres.
    """
    cuts: list[float] = []
    n = len(centres)
    while True:
        gone = far.below(edge) if count == "live" else centres.below(edge)
        if n - gone <= payload:
            return cuts
        at = gone + payload
        if min_fresh:
            at = max(at, centres.below(edge) + min_fresh)
        if at >= n:
            return cuts
        cut = centres[at]
        if cut <= edge:
            cut = centres.beyond(edge)
            if cut is None:
                return cuts
        edge = cut
        cuts.append(edge)


def tiles_of_cuts(region: Box, cuts: list[float], axis: str = "x") -> list[Tile]:
    ends = [region.low(axis), *cuts, region.high(axis)]
    if axis == "x":
        return [(a, region.ymin, z, region.ymax, None) for a, z in zip(ends, ends[1:])]
    return [(region.xmin, a, region.xmax, z, None) for a, z in zip(ends, ends[1:])]


def split_tree(b: np.ndarray, region: Box, payload: int, max_depth: int = 40, max_cross: float | None = None, cut: str = "median") -> list[Tile]:
    """Halves nodes of more than `payload` boxes at a median centre (or in the middle)."""
    out: list[Tile] = []
    todo = [(region, np.arange(len(b)), 0)]
    c = _centres(b)
    while todo:
        node, own, depth = todo.pop()
        choice = None
        if len(own) > payload and depth < max_depth:
            for d, axis in enumerate("xy"):
                lo, hi = node.low(axis), node.high(axis)
                at = float(np.sort(c[own, d])[(len(own) - 1) // 2]) if cut == "median" else (lo + hi) / 2
                if lo < at < hi:
                    f = (at - lo) / (hi - lo)
                    if choice is None or f * (1 - f) > choice[0]:
                        choice = (f * (1 - f), d, at)
        if choice:
            _, d, at = choice
            left, right = own[b[own, d] < at], own[b[own, d + 2] >= at]
            crossing = len(left) + len(right) - len(own)
            if not len(left) or not len(right) or len(left) == len(right) == len(own) or (max_cross is not None and crossing > max_cross * len(own)):
                choice = None
        if not choice:
            out.append((node.xmin, node.ymin, node.xmax, node.ymax, len(own)))
        elif d == 0:
            todo += [(Box(at, node.ymin, node.xmax, node.ymax), right, depth + 1), (Box(node.xmin, node.ymin, at, node.ymax), left, depth + 1)]
        else:
            todo += [(Box(node.xmin, at, node.xmax, node.ymax), right, depth + 1), (Box(node.xmin, node.ymin, node.xmax, at), left, depth + 1)]
    return out


def split_incremental(b: np.ndarray, region: Box, payload: int, max_depth: int = 40) -> list[Tile]:
    """Boxes arrive one by one; a leaf that overflows is cut at the median of what it holds."""
    leaves: list[tuple[Box, list[int], int]] = [(region, [], 0)]

    def meets(node: Box, i: int) -> bool:
        x0, y0, x1, y1 = b[i]
        return (
            x1 >= node.xmin and (x0 < node.xmax or node.xmax >= region.xmax) and y1 >= node.ymin and (y0 < node.ymax or node.ymax >= region.ymax)
        )

    for i in range(len(b)):
        for k in [k for k, leaf in enumerate(leaves) if meets(leaf[0], i)]:
            node, own, depth = leaves[k]
            own.append(i)
            if len(own) <= payload or depth >= max_depth:
                continue
            parts = split_tree(b[own], node, len(own) - 1, max_depth=1)
            if len(parts) == 2:
                halves = [(Box(*p[:4]), [], depth + 1) for p in parts]
                for node2, own2, _ in halves:
                    own2 += [j for j in own if meets(node2, j)]
                leaves[k] = halves[0]
                leaves.append(halves[1])
    return [(n.xmin, n.ymin, n.xmax, n.ymax, len(own)) for n, own, _ in leaves]


def sort_tiles(b: np.ndarray, region: Box, payload: int, edges: str = "tight") -> list[Tile]:
    """Slabs by centre x, tiles by centre y, where equal ones stay in the slab's order. edges `slab`: cuts at centres, which tile the region."""
    if not len(b):
        return [(region.xmin, region.ymin, region.xmax, region.ymax, 0)]
    c = _centres(b)
    m = int(np.ceil(np.sqrt(len(b) / payload)))
    by_x = np.lexsort((np.arange(len(b)), c[:, 0]))
    out: list[Tile] = []
    slabs = [by_x[i : i + m * payload] for i in range(0, len(b), m * payload)]
    for s, own in enumerate(slabs):
        own = own[np.argsort(c[own, 1], kind="stable")]
        groups = [own[i : i + payload] for i in range(0, len(own), payload)]
        x0 = region.xmin if s == 0 else float(c[slabs[s], 0].min())
        x1 = region.xmax if s + 1 == len(slabs) else float(c[slabs[s + 1], 0].min())
        for t, g in enumerate(groups):
            if edges == "tight":
                out.append((*map(float, b[g, :2].min(0)), *map(float, b[g, 2:].max(0)), len(g)))
            elif x0 < x1:
                y0 = region.ymin if t == 0 else float(c[g[0], 1])
                y1 = region.ymax if t + 1 == len(groups) else float(c[groups[t + 1][0], 1])
                if y0 < y1:
                    out.append((x0, y0, x1, y1, len(g)))
    return out


def optimal_1d(centres: Sorted, far: Sorted, near: Sorted, tiles: int) -> tuple[list[float], int]:
    """Cuts of at most `tiles` strips at centres whose largest load is least, and that load.

    Binary search on the load; a sweep tells whether it is enough.
    """
    spots = centres.values
    at = np.searchsorted(near.values, spots)
    started = np.where(at > 0, near.upto[at - 1], 0)

    def sweep(load: int) -> list[float] | None:
        cuts: list[float] = []
        edge = -np.inf
        while True:
            gone = far.below(edge)
            if len(far) - gone <= load:
                return cuts
            # The farthest cut c with (boxes beginning before c) - gone <= load.
            last = int(np.searchsorted(started, gone + load, "right")) - 1
            if last < 0 or spots[last] <= edge or len(cuts) + 1 >= tiles:
                return None
            edge = float(spots[last])
            cuts.append(edge)

    low, high = 0, len(far)
    while low < high:
        mid = (low + high) // 2
        if sweep(mid) is None:
            low = mid + 1
        else:
            high = mid
    return sweep(low) or [], low


KERNELS = {
    "binary": split_tree,
    "strip": strips,
    "least_cut": peel,
    "sort_tile": sort_tiles,
}
