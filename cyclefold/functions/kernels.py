"""Local numpy kernels that run inside grouped Arrow/pandas functions, one recording at a time.

Every kernel takes plain arrays and has no Spark in it, so the same code serves the
distributed pipeline, the SQL functions and the tests.
"""

from __future__ import annotations

import numpy as np

# --- distances --------------------------------------------------------------------------------


def squared_distances(x: np.ndarray) -> np.ndarray:
    """All squared Euclidean distances between rows, exactly symmetric with a zero diagonal."""
    x = np.asarray(x, np.float64)
    x = x - x.mean(axis=0)
    g = x @ x.T
    n = np.diag(g)
    d2 = np.maximum(n[:, None] + n[None] - 2 * g, 0)
    d2 = np.minimum(d2, d2.T)
    scale = float(n.max()) if len(n) else 0.0
    d2[d2 < 1e-13 * max(scale, 1e-300)] = 0.0
    np.fill_diagonal(d2, 0)
    return d2


def squared_differences(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances of the rows of a to those of b, by differences, so that equal rows are equally far from any other."""
    b = b.astype(np.float64)
    far, apart = np.empty((len(a), len(b))), np.empty_like(b)
    for k, row in enumerate(a.astype(np.float64)):
        np.subtract(b, row, out=apart)
        np.einsum("jk,jk->j", apart, apart, out=far[k])
    return far


def window_distances(d2: np.ndarray, d: int) -> np.ndarray:
    """Squared distances of windows of d frames: sums of d entries along each diagonal.

    Running sums of the whole matrix along its diagonals, so the cost does not depend on d.
    """
    n = len(d2)
    if d <= 1:
        return d2.copy()
    if n < d:
        return np.zeros((0, 0))
    total = np.zeros((n + 1, n + 1))
    for i in range(n):
        total[i + 1, 1:] = total[i, :-1] + d2[i]
    out = total[d:, d:] - total[:-d, :-d]
    out = np.maximum((out + out.T) / 2, 0)
    np.fill_diagonal(out, 0)
    return out


def isometric_projection(x: np.ndarray, rank: int | None = None) -> np.ndarray:
    """Coordinates in at most N-1 dimensions with the rows' pairwise distances."""
    x = np.asarray(x, np.float64)
    x = x - x.mean(axis=0)
    values, vectors = np.linalg.eigh(x @ x.T)
    keep = min(len(x) - 1, x.shape[1]) if rank is None else rank
    order = np.argsort(values)[::-1][:keep]
    return vectors[:, order] * np.sqrt(np.maximum(values[order], 0))


# --- period -----------------------------------------------------------------------------------


def knn_graph(d2: np.ndarray, k: int = 8) -> np.ndarray:
    """Lengths of the symmetrised k-nearest-neighbour graph, infinite where there is no edge.

    Components are joined by their nearest pairs, so that exact repeats stay connected.
    """
    n = len(d2)
    length = np.sqrt(d2)
    graph = np.full((n, n), np.inf)
    order = np.argsort(d2 + np.diag(np.full(n, np.inf)), axis=1, kind="stable")[:, : min(k, n - 1)]
    rows = np.arange(n)[:, None]
    graph[rows, order] = length[rows, order]
    graph = np.minimum(graph, graph.T)
    np.fill_diagonal(graph, 0)
    label = _components(np.isfinite(graph))
    while label.max() > 0:
        apart = np.where(label[:, None] != label[None], length, np.inf)
        i, j = np.unravel_index(np.argmin(apart), apart.shape)
        graph[i, j] = graph[j, i] = length[i, j]
        low, high = sorted((label[i], label[j]))
        label[label == high] = low
        _, label = np.unique(label, return_inverse=True)
    return graph


def _components(linked: np.ndarray) -> np.ndarray:
    n = len(linked)
    label = np.full(n, -1)
    found = 0
    for start in range(n):
        if label[start] < 0:
            todo = [start]
            label[start] = found
            while todo:
                new = np.flatnonzero(linked[todo.pop()] & (label < 0))
                label[new] = found
                todo += new.tolist()
            found += 1
    return label


def geodesics(graph: np.ndarray) -> np.ndarray:
    """All shortest paths; one vectorised relaxation per intermediate node."""
    path = graph.copy()
    for k in range(len(path)):
        np.minimum(path, path[:, k, None] + path[None, k], out=path)
    return path


def spanning_edges(i: np.ndarray, j: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Indices of the edges i, j of length w that are a minimal spanning forest; equal lengths go by i, then j.

    Every component takes its shortest edge out at once, until no edge leads out of one.
    """
    m = len(w)
    nodes, ends = np.unique(np.concatenate([i, j]), return_inverse=True)
    order = np.lexsort((j, i, w))
    a, b = ends[:m][order], ends[m:][order]
    kept, label, at = np.zeros(m, bool), np.arange(len(nodes)), np.arange(m)
    while len(at):
        first = np.full(len(nodes), m)
        for end in (a, b):
            of = np.full(len(nodes), m)
            of[label[end[at]][::-1]] = at[::-1]  # the last that is written is the first edge
            np.minimum(first, of, out=first)
        c = np.flatnonzero(first < m)
        one, two = label[a[first[c]]], label[b[first[c]]]
        kept[first[c]] = True
        to = np.arange(len(nodes))
        to[c] = np.where(one == c, two, one)
        root = c[(to[to[c]] == c) & (c < to[c])]
        to[root] = root
        while (to[to] != to).any():
            to = to[to]
        label = to[label]
        at = at[label[a[at]] != label[b[at]]]
    return np.sort(order[kept])


def linked_neighbours(i: np.ndarray, j: np.ndarray, d2: np.ndarray) -> tuple[np.ndarray, ...]:
    """(order, counts, sources, lengths): edges both ways as slots of nodes that are ordered by falling degree.

    Slot k of ``sources`` has the k-th neighbour, as a place in that order, of the first ``counts[k]`` nodes.
    """
    ends = np.unique(np.stack([np.concatenate([i, j]), np.concatenate([j, i])]).astype(np.int64), axis=1, return_index=True)
    (to, source), length = ends[0], np.sqrt(np.concatenate([d2, d2])[ends[1]])
    degree = np.bincount(to)
    order = np.argsort(-degree, kind="stable")
    place = np.argsort(order)
    slot = np.arange(len(to)) - (np.cumsum(degree) - degree)[to]
    by_slot = np.lexsort((place[to], slot))
    return order, np.bincount(slot), place[source[by_slot]], length[by_slot]


def paths_from(graph: tuple[np.ndarray, ...], starts: np.ndarray) -> np.ndarray:
    """Shortest paths along ``linked_neighbours`` from some nodes to all: a row a node, a column a start."""
    order, counts, sources, lengths = graph
    place = np.argsort(order)
    far = np.full((len(order), len(starts)), np.inf)
    far[place[starts], np.arange(len(starts))] = 0
    cuts = np.cumsum(counts)
    while True:
        new = far.copy()
        for n, end in zip(counts, cuts, strict=True):
            step = far[sources[end - n : end]]
            step += lengths[end - n : end, None]
            np.minimum(new[:n], step, out=new[:n])
        if np.array_equal(new, far):
            return far[place]
        far = new


def landmark_order(d2: np.ndarray, m: int, start: int = 0) -> tuple[np.ndarray, float]:
    """Farthest-point order of m points and the radius within which they cover all (not squared)."""
    chosen, nearest = [start], d2[start].copy()
    while len(chosen) < min(m, len(d2)):
        far = int(np.argmax(nearest))
        if nearest[far] <= 0:
            break
        chosen.append(far)
        np.minimum(nearest, d2[far], out=nearest)
    return np.array(chosen), float(np.sqrt(nearest.max()))


def isomap1d(d2: np.ndarray, k: int = 8, landmarks: int | None = None) -> np.ndarray:
    """One coordinate that keeps geodesic distances best; largest entry positive."""
    graph = knn_graph(d2, k)
    n = len(d2)
    if landmarks is None or landmarks >= n:
        g2 = geodesics(graph) ** 2
        b = -0.5 * (g2 - g2.mean(0) - g2.mean(1)[:, None] + g2.mean())
        values, vectors = np.linalg.eigh(b)
        y = vectors[:, -1] * np.sqrt(max(values[-1], 0))
    else:
        marks, _ = landmark_order(d2, landmarks)
        to_all = np.stack([_dijkstra(graph, s) for s in marks]) ** 2
        own = to_all[:, marks]
        mean = own.mean(1)
        b = -0.5 * (own - own.mean(0) - mean[:, None] + own.mean())
        values, vectors = np.linalg.eigh(b)
        y = -0.5 * (vectors[:, -1] / np.sqrt(max(values[-1], 1e-300))) @ (to_all - mean[:, None])
    at = np.argmax(np.abs(y))
    return y * (1.0 if y[at] >= 0 else -1.0)


def _dijkstra(graph: np.ndarray, source: int) -> np.ndarray:
    far, done = np.full(len(graph), np.inf), np.zeros(len(graph), bool)
    far[source] = 0
    for _ in range(len(graph)):
        u = int(np.argmin(np.where(done, np.inf, far)))
        if not np.isfinite(far[u]):
            break
        done[u] = True
        np.minimum(far, far[u] + graph[u], out=far)
    return far


def autocorrelation(x: np.ndarray, most: int, method: str = "acf") -> np.ndarray:
    """Values for the lags 0..most. acf: mean removed, normalised by the overlap; nsdf: McLeod's
    normalisation by both halves' energy; yin: one minus the cumulative-mean-normalised difference."""
    x = np.asarray(x, np.float64)
    x = x - x.mean()
    n = len(x)
    size = 1 << int(2 * n - 1).bit_length()
    f = np.fft.rfft(x, size)
    r = np.fft.irfft(f * np.conj(f), size)[: most + 1]
    count = n - np.arange(most + 1)
    energy = np.cumsum(np.r_[0, x * x])
    both = energy[count] + energy[n] - energy[n - count]
    if method == "acf":
        top = r[0] / n
        return r / count / (top if top > 0 else 1.0)
    if method == "nsdf":
        return 2 * r / np.where(both > 0, both, 1.0)
    if method == "yin":
        difference = np.maximum(both - 2 * r, 0) / count
        mean = np.cumsum(difference[1:]) / np.arange(1, most + 1)
        return np.r_[1.0, 1 - difference[1:] / np.where(mean > 0, mean, 1.0)]
    raise ValueError(f"unknown period method {method!r}")


def period(x: np.ndarray, method: str = "acf", tmin: int = 3, tmax: int | None = None, key: float = 0.8) -> tuple[float, float]:
    """(period, its autocorrelation): the first local maximum that comes near the highest one.

    Maxima count from the first zero crossing on; a parabola through the three values at the
    maximum refines it. Without any maximum the period is nan.
    """
    most = min(len(x) // 2 if tmax is None else tmax, len(x) - 2)
    if most < tmin:
        return float("nan"), 0.0
    return first_peak(autocorrelation(x, most + 1, method), tmin, key)


def matrix_autocorrelation(d2: np.ndarray, most: int) -> np.ndarray:
    """The autocorrelation of all coordinates together, from squared distances: mean inner products by lag."""
    mean = d2.mean(axis=1)
    g = -0.5 * (d2 - mean - mean[:, None] + d2.mean())
    r = np.array([np.diagonal(g, lag).mean() for lag in range(most + 1)])
    r[0] = 2 * r[1] - r[2] if most > 1 else r[0]  # a frame's own noise is in no other lag
    return r / (r[0] if r[0] > 0 else 1.0)


def matrix_period(d2: np.ndarray, tmin: int = 3, tmax: int | None = None, key: float = 0.8) -> tuple[float, float]:
    most = min(len(d2) // 2 if tmax is None else tmax, len(d2) - 2)
    return first_peak(matrix_autocorrelation(d2, most + 1), tmin, key) if most >= tmin else (float("nan"), 0.0)


def first_peak(r: np.ndarray, tmin: int = 3, key: float = 0.8) -> tuple[float, float]:
    """(lag, value) of the first key maximum of an autocorrelation for the lags 0 to one more than are looked at."""
    most = len(r) - 2
    below = np.flatnonzero(r[1:] <= 0)
    start = max(tmin, int(below[0]) + 1 if len(below) else tmin)
    inner = np.arange(max(start, 1), most + 1)
    inner = inner[(r[inner] >= r[inner - 1]) & (r[inner] > r[inner + 1]) & (r[inner] > 0)]
    if not len(inner):
        return float("nan"), 0.0
    at = int(inner[np.argmax(r[inner] >= key * r[inner].max())])
    a, b, c = r[at - 1 : at + 2]
    bend = a - 2 * b + c
    return at + (0.5 * (a - c) / bend if bend < 0 else 0.0), float(b)


# --- persistent homology ----------------------------------------------------------------------


def field_characteristic(coeff: int) -> int:
    """The prime p of a field with ``coeff`` elements; 49 names the field of 49 elements, so 7."""
    for p in range(2, coeff + 1):
        if coeff % p == 0:
            q = coeff
            while q % p == 0:
                q //= p
            if q != 1 or (coeff != p and coeff != 49):
                break
            return p
    raise ValueError(f"coefficients must be a prime or 49, not {coeff}")


def rips_h1(dist: np.ndarray, coeff: int = 7) -> np.ndarray:
    """Rows (birth, death) of the one-dimensional Rips barcode, most persistent first.

    Edges come in order of (length, i, j) up to the enclosing radius, beyond which nothing
    survives. Every edge carries its values under a basis of the living cocycles. An edge that
    closes a cycle without a triangle begins a class; one with a triangle takes its value from
    it; every further triangle whose values do not add up ends the youngest class in the sum,
    which is then eliminated from all edges. Only classes that live for a while are kept.
    """
    p = field_characteristic(coeff)
    n = len(dist)
    if n < 3:
        return np.zeros((0, 2))
    limit = dist.max(axis=1).min()
    i, j = np.triu_indices(n, 1)
    length = dist[i, j]
    keep = length <= limit
    i, j, length = i[keep], j[keep], length[keep]
    order = np.lexsort((j, i, length))
    i, j, length = i[order], j[order], length[order]
    rank = np.full((n, n), len(i), np.int64)
    rank[i, j] = rank[j, i] = np.arange(len(i))
    np.fill_diagonal(rank, len(i))
    inverse = [0] + [pow(a, -1, p) for a in range(1, p)]
    root = np.arange(n)
    width = 8
    value = np.zeros((n, n, width), np.int16)
    born: list[float | None] = [None] * width  # birth of the class in each column
    age: list[int] = [-1] * width
    bars: list[tuple[float, float]] = []
    for e in range(len(i)):
        a, b, now = int(i[e]), int(j[e]), float(length[e])
        if root[a] != root[b]:
            root[root == root[b]] = root[a]
            continue
        third = np.flatnonzero((rank[a] < e) & (rank[b] < e))
        if not len(third):
            try:
                c = born.index(None)
            except ValueError:
                c = width
                width *= 2
                value = np.concatenate([value, np.zeros_like(value)], axis=2)
                born += [None] * (width - c)
                age += [-1] * (width - c)
            born[c], age[c] = now, e
            value[a, b, c], value[b, a, c] = 1, p - 1
            continue
        k = third[0]
        own = (value[a, k] - value[b, k]) % p
        value[a, b], value[b, a] = own, (-own) % p
        while True:
            around = (value[a, b] + value[b, third] - value[a, third]) % p
            odd = np.flatnonzero(around.any(axis=1))
            if not len(odd):
                break
            sum_ = around[odd[0]]
            c = max(np.flatnonzero(sum_), key=lambda x: age[x])
            if now > born[c]:
                bars.append((born[c], now))
            born[c], age[c] = None, -1
            share = (sum_ * inverse[int(sum_[c])]) % p
            column = value[:, :, c].copy()
            x, y = np.nonzero(column)
            value[x, y] = (value[x, y] - column[x, y, None] * share) % p
    bars.sort(key=lambda bar: (bar[0] - bar[1], bar[0]))
    return np.array(bars, np.float64).reshape(-1, 2)


def h0_deaths(dist: np.ndarray) -> np.ndarray:
    """Lengths of a minimal spanning tree's edges, ascending."""
    n = len(dist)
    if n < 2:
        return np.zeros(0)
    inside = np.zeros(n, bool)
    nearest = dist[0].copy()
    inside[0] = True
    out = []
    for _ in range(n - 1):
        k = int(np.argmin(np.where(inside, np.inf, nearest)))
        out.append(nearest[k])
        inside[k] = True
        np.minimum(nearest, dist[k], out=nearest)
    return np.sort(out)


def auto_scale(bars: np.ndarray, alpha: float, dist: np.ndarray | None = None) -> tuple[float, bool]:
    """(sigma, fallback): birth and death of the most persistent class blended by alpha.

    Without a class: the largest nearest-neighbour distance and the enclosing radius.
    """
    if len(bars):
        best = min(map(tuple, bars), key=lambda b: (-(b[1] - b[0]), b[0]))
        return float(alpha * best[0] + (1 - alpha) * best[1]), False
    if dist is None or len(dist) < 2:
        return 0.0, True
    apart = dist + np.diag(np.full(len(dist), np.inf))
    return float(alpha * apart.min(axis=1).max() + (1 - alpha) * dist.max(axis=1).min()), True


# --- graph and phase --------------------------------------------------------------------------


def adjacency(dist: np.ndarray, sigma: float, kernel: str = "gauss") -> np.ndarray:
    """step: 1 within sigma; gauss: exp(-d^2 / 2 sigma^2); printed: exp(-d / 2 sigma^2); zero diagonal."""
    if kernel == "step":
        a = (dist <= sigma).astype(np.float64)
    elif kernel == "gauss":
        a = np.exp(-(dist**2) / (2 * max(sigma, 1e-300) ** 2))
    elif kernel == "printed":
        a = np.exp(-dist / (2 * max(sigma, 1e-150) ** 2))
    else:
        raise ValueError(f"unknown kernel {kernel!r}")
    np.fill_diagonal(a, 0)
    return a


def laplacian(a: np.ndarray) -> np.ndarray:
    return np.diag(a.sum(axis=1)) - a


def low_modes(lap: np.ndarray, q: int = 10) -> tuple[np.ndarray, np.ndarray, int]:
    """The q lowest eigenvalues that are not zero with their vectors, and the number of zero ones."""
    values, vectors = np.linalg.eigh(lap)
    zero = values <= 1e-9 * max(values[-1], 1e-300)
    values, vectors = values[~zero][:q], vectors[:, ~zero][:, :q]
    at = np.argmax(np.abs(vectors), axis=0) if vectors.size else np.zeros(0, int)
    return values, vectors * np.where(vectors[at, np.arange(len(at))] < 0, -1.0, 1.0), int(zero.sum())


def zero_crossings(v: np.ndarray) -> int:
    """Sign changes along the vector; zeros take the sign before them."""
    s = np.sign(v)
    s = s[s != 0]
    return int((s[1:] != s[:-1]).sum())


def mode_pair(counts: list[int], tol: float = 0.2) -> tuple[int, int, bool]:
    """Neighbouring ranks with the fewest crossings whose counts agree within ``tol``; the first two if none do."""
    best = None
    for r in range(len(counts) - 1):
        low, high = sorted(counts[r : r + 2])
        if low >= 1 and high <= (1 + tol) * low and (best is None or low + high < best[0]):
            best = low + high, r
    return (best[1], best[1] + 1, False) if best else (0, 1, True)


def phase(vectors: np.ndarray, pair: tuple[int, int]) -> np.ndarray:
    return np.arctan2(vectors[:, pair[0]], vectors[:, pair[1]]) % (2 * np.pi)


def wrap(x):
    """Into (-pi, pi]."""
    return -((-np.asarray(x) + np.pi) % (2 * np.pi) - np.pi)


def unwrap(phi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(oriented phase, unwrapped phase from zero): direction such that the median step is forward."""
    step = wrap(np.diff(phi))
    if len(step) and np.median(step) < 0:
        phi, step = (-phi) % (2 * np.pi), -step
    return phi, np.r_[0.0, np.cumsum(step)]


def cycle_count(unwrapped: np.ndarray, frames: int, d: int, how: str = "printed") -> float:
    if how == "printed":
        return frames * float(unwrapped.max()) / (2 * np.pi * (frames - d + 1))
    if how == "slope":
        t = np.arange(len(unwrapped)) - (len(unwrapped) - 1) / 2
        return frames * float(t @ unwrapped) / float(t @ t) / (2 * np.pi) if len(t) > 1 else 0.0
    raise ValueError(f"unknown cycle count {how!r}")


def angular_error(estimate: np.ndarray, truth: np.ndarray) -> float:
    """Mean wrapped difference in degrees after the best offset, in the better of both directions."""
    errors = []
    for sign in (1, -1):
        difference = sign * estimate - truth
        offset = np.arctan2(np.sin(difference).mean(), np.cos(difference).mean())
        errors.append(np.degrees(np.abs(wrap(difference - offset)).mean()))
    return float(min(errors))


# --- votes ------------------------------------------------------------------------------------


def votes(phi: np.ndarray, angles: np.ndarray, k: float, frames: int, d: int, near: float | None = None, anchor: str = "start"):
    """(j, i, a, b, frac, offset): window i votes for angle j with frames a and b blended by frac.

    The offset is the angle's place in the window, in frames; windows longer than a cycle
    vote once per cycle. ``near`` keeps votes at most so far from the window's anchor.
    """
    turn = frames / k if k > 0 else np.inf
    first = ((angles[None] - phi[:, None]) % (2 * np.pi)) * (turn / (2 * np.pi)) if np.isfinite(turn) else np.zeros((len(phi), len(angles)))
    out = []
    for c in range(int((d - 1) // turn) + 1 if np.isfinite(turn) else 1):
        offset = first + c * turn if np.isfinite(turn) else first
        ok = offset <= d - 1
        if near is not None:
            centre = 0 if anchor == "start" else (d - 1) / 2
            ok &= np.abs(offset - centre) <= near
        i, j = np.nonzero(ok)
        s = offset[i, j]
        whole = np.floor(s).astype(np.int64)
        out.append((j, i, i + whole, np.minimum(i + whole + 1, i + d - 1), s - whole, s))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def median_template(pixels: np.ndarray, vote: tuple, m: int) -> tuple[np.ndarray, np.ndarray]:
    """(m x pixels medians, votes per angle); nan where an angle has no vote."""
    j, _, a, b, frac, _ = vote
    order = np.argsort(j, kind="stable")
    j, a, b, frac = j[order], a[order], b[order], frac[order]
    cuts = np.searchsorted(j, np.arange(m + 1))
    out = np.full((m, pixels.shape[1]), np.nan)
    for k in range(m):
        s = slice(cuts[k], cuts[k + 1])
        if cuts[k] < cuts[k + 1]:
            w = frac[s, None]
            out[k] = np.median((1 - w) * pixels[a[s]] + w * pixels[b[s]], axis=0)
    return out, np.diff(cuts)
