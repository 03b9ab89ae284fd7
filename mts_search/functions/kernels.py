"""Array kernels for one chunk or one window: distances, sliding spectra, bounds, pivots. No Spark in here."""

from __future__ import annotations

from functools import lru_cache

import numpy as np


def bins_of(q: int) -> int:
    """Bins of the one-sided spectrum of a real window of length q."""
    return q // 2 + 1


def bin_weight(b: int, q: int) -> float:
    """How often a one-sided bin stands in the full spectrum."""
    return 1.0 if b == 0 or 2 * b == q else 2.0


def dims_of(q: int, kept: dict[int, list[int]], normalized: bool = False) -> list[tuple[int, int, str, float]]:
    """Feature dimensions (channel, bin, part, scale); scaled so that their Euclidean distance is a lower bound itself."""
    out = []
    for c in sorted(kept):
        for b in kept[c]:
            if normalized and b == 0:
                continue  # the mean of a normalised window is 0
            scale = float(np.sqrt(bin_weight(b, q) / q))
            out.append((c, b, "re", scale))
            if b and 2 * b != q:
                out.append((c, b, "im", scale))
    return out


def znorm(x: np.ndarray) -> np.ndarray:
    """Normalised rows (population deviation); constant rows become 0."""
    mean = x.mean(axis=-1, keepdims=True)
    std = x.std(axis=-1, keepdims=True)
    return np.where(std > 1e-12 * np.maximum(1, np.abs(mean)), (x - mean) / np.where(std > 0, std, 1), 0.0)


def window_stats(x: np.ndarray, q: int) -> tuple[np.ndarray, np.ndarray]:
    """Mean and population deviation of every window of the rows of ``x`` (c, m); sums run over centred values."""
    centre = x.mean(axis=1, keepdims=True)
    y = x - centre
    s1 = np.concatenate([np.zeros((len(x), 1)), np.cumsum(y, axis=1)], axis=1)
    s2 = np.concatenate([np.zeros((len(x), 1)), np.cumsum(y * y, axis=1)], axis=1)
    mean = (s1[:, q:] - s1[:, :-q]) / q
    var = np.maximum((s2[:, q:] - s2[:, :-q]) / q - mean * mean, 0.0)
    std = np.sqrt(var)
    scale = np.maximum(1.0, np.abs(y).max(axis=1, keepdims=True) if y.shape[1] else 1.0)
    std = np.where(std > 1e-7 * scale, std, 0.0)
    return mean + centre, std


@lru_cache(maxsize=256)
def _turns(b: int, q: int, m: int) -> tuple[np.ndarray, np.ndarray]:
    """Factors of a bin at every place of a chunk and, turned back, at every start; the same for all chunks of a length."""
    t = np.arange(m)
    return np.exp(-2j * np.pi * (b * t % q) / q), np.exp(2j * np.pi * (b * t[: m - q + 1] % q) / q)


def sliding_features(x: np.ndarray, q: int, dims: list[tuple[int, int, str, float]], normalized: bool = False) -> np.ndarray:
    """Features of every window of a chunk (c, m): prefix sums of modulated values, then a turn by the start."""
    m = x.shape[1]
    n = m - q + 1
    if n <= 0:
        return np.zeros((0, len(dims)))
    out = np.empty((n, len(dims)))
    std = window_stats(x, q)[1] if normalized else None
    cache: dict[tuple[int, int], np.ndarray] = {}
    means: dict[int, float] = {}
    for d, (c, b, part, scale) in enumerate(dims):
        z = cache.get((c, b))
        if z is None:
            if b and c not in means:
                means[c] = x[c].mean()
            y = x[c] - (means[c] if b else 0.0)  # a constant only moves bin 0
            back, turn = _turns(b, q, m)
            run = np.concatenate([[0], np.cumsum(y * back)])
            z = (run[q:] - run[:-q]) * turn
            if normalized:
                z = np.divide(z, std[c], out=np.zeros_like(z), where=std[c] > 0)
            cache[(c, b)] = z
        out[:, d] = (z.real if part == "re" else z.imag) * scale
    return out


def window_features(w: np.ndarray, dims: list[tuple[int, int, str, float]], normalized: bool = False) -> np.ndarray:
    """Features of single windows (..., c, q)."""
    if normalized:
        w = znorm(w)
    spec = np.fft.rfft(w, axis=-1)
    return np.stack([(spec[..., c, b].real if part == "re" else spec[..., c, b].imag) * scale for c, b, part, scale in dims], axis=-1) if dims else np.zeros((*w.shape[:-2], 0))


def remainder(w: np.ndarray, kept: dict[int, list[int]], normalized: bool = False) -> np.ndarray:
    """Windows (..., c, q) without their kept bins."""
    if normalized:
        w = znorm(w)
    spec = np.fft.rfft(w, axis=-1)
    for c, bins in kept.items():
        spec[..., c, bins] = 0
    return np.fft.irfft(spec, n=w.shape[-1], axis=-1)


def reconstruct(w: np.ndarray, bins: list[int]) -> tuple[np.ndarray, float]:
    """A series from the given bins only, and the root mean squared error."""
    spec = np.fft.rfft(w)
    keep = np.zeros_like(spec)
    keep[bins] = spec[bins]
    back = np.fft.irfft(keep, n=len(w))
    return back, float(np.sqrt(np.mean((back - w) ** 2)))


def sliding_dots(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Dot product of ``y`` with every window of ``x`` (one channel) by the convolution theorem, or directly if short."""
    m, q = len(x), len(y)
    if m - q + 1 < 4 * np.log2(m + 2):
        return np.lib.stride_tricks.sliding_window_view(x, q) @ y
    size = 1 << int(np.ceil(np.log2(m + q)))
    return np.fft.irfft(np.fft.rfft(x, size) * np.fft.rfft(y[::-1], size), size)[q - 1 : m]


def profile(x: np.ndarray, y: np.ndarray, normalized: bool = False, method: str = "auto") -> np.ndarray:
    """Squared distances of the query ``y`` (c, q) to every window of ``x`` (c, m), all at once."""
    q = y.shape[1]
    n = x.shape[1] - q + 1
    if n <= 0:
        return np.zeros(0)
    if method == "direct" or method == "auto" and n < 4 * np.log2(x.shape[1] + 2):
        w = np.lib.stride_tricks.sliding_window_view(x, q, axis=1)
        if normalized:
            return ((znorm(w) - znorm(y)[:, None, :]) ** 2).sum(axis=(0, 2))
        d = w - y[:, None, :]
        return np.einsum("cnq,cnq->n", d, d)
    total = np.zeros(n)
    if normalized:
        mean, std = window_stats(x, q)
        yz = znorm(y)
        for c in range(len(x)):
            flat_y = not yz[c].any()
            dots = sliding_dots(x[c] - x[c].mean(), yz[c])
            with np.errstate(divide="ignore", invalid="ignore"):
                d = 2 * q - 2 * dots / std[c]
            flat = std[c] == 0
            total += np.where(flat, 0.0 if flat_y else q, q if flat_y else d)
        return np.maximum(total, 0)
    for c in range(len(x)):
        centre = x[c].mean()
        a, b = x[c] - centre, y[c] - centre
        run = np.concatenate([[0], np.cumsum(a * a)])
        total += run[q:] - run[:-q] - 2 * sliding_dots(a, b) + (b * b).sum()
    return np.maximum(total, 0)


def profiles(x: np.ndarray, ys: np.ndarray, normalized: bool = False, method: str = "auto") -> np.ndarray:
    """Profiles of several queries (n, c, q) of the same channels; the chunk's transforms and running sums are made once."""
    q, m = ys.shape[2], x.shape[1]
    few = m - q + 1 < 4 * np.log2(m + 2)
    if len(ys) == 1 or normalized or few or method == "direct":
        return np.array([profile(x, y, normalized, method) for y in ys])
    total = np.zeros((len(ys), m - q + 1))
    size = 1 << int(np.ceil(np.log2(m + q)))
    for c in range(len(x)):
        centre = x[c].mean()
        a, b = x[c] - centre, ys[:, c] - centre
        run = np.concatenate([[0], np.cumsum(a * a)])
        dots = np.fft.irfft(np.fft.rfft(a, size) * np.fft.rfft(b[:, ::-1], size, axis=1), size, axis=1)[:, q - 1 : m]
        total += run[q:] - run[:-q] - 2 * dots + (b * b).sum(axis=1)[:, None]
    return np.maximum(total, 0)


def direct(x: np.ndarray, y: np.ndarray, starts: np.ndarray, normalized: bool = False) -> np.ndarray:
    """Squared distances of single windows, value by value; exact for whole numbers."""
    q = y.shape[1]
    w = x[:, starts[:, None] + np.arange(q)]
    if normalized:
        w, y = znorm(w), znorm(y)
    return ((w - y[:, None, :]) ** 2).sum(axis=(0, 2))


def nearest(x: np.ndarray, y: np.ndarray, q: int) -> np.ndarray:
    """Squared distance of every window of x to its nearest window of y; exact for whole numbers.

    Running sums along the diagonals of the squared differences give all pairs of starts, a row of sums at a time.
    """
    n, m = len(x) - q + 1, len(y) - q + 1
    if n <= 0 or m <= 0:
        return np.zeros(0, x.dtype)
    best = np.empty(n, x.dtype)
    run = np.zeros((q + 1, len(y) + 1), x.dtype)  # rows of running sums, the last q + 1 of them
    for i in range(1, len(x) + 1):
        run[i % (q + 1), 1:] = run[(i - 1) % (q + 1), :-1] + (x[i - 1] - y) ** 2
        if i >= q:
            best[i - q] = (run[i % (q + 1), q:] - run[(i - q) % (q + 1), :m]).min()
    return best


def pivot_gaps(x: np.ndarray, q: int, dims, features: np.ndarray, pivots: np.ndarray, normalized: bool = False) -> np.ndarray:
    """Distance of every window's remainder to each pivot, by channel: (windows, channels * pivots).

    No remainder is built: pivots lie in the complement of the kept bins, so the product of remainder and pivot
    is that of window and pivot.
    """
    c, m = x.shape
    n = m - q + 1
    p = len(pivots)
    out = np.zeros((n, c * p))
    mean, std = window_stats(x, q)
    own_dims: dict[int, list[int]] = {}
    for d, (k, *_rest) in enumerate(dims):
        own_dims.setdefault(k, []).append(d)
    for ch in range(c):
        kept = own_dims.get(ch, [])
        if normalized:
            norm = np.where(std[ch] > 0, float(q), 0.0)
            own = x[ch] - x[ch].mean()
        else:
            own = x[ch] - x[ch].mean()
            norm = q * (std[ch] ** 2 + mean[ch] ** 2)
        rest = np.maximum(norm - (features[:, kept] ** 2).sum(axis=1), 0)
        for j in range(p):
            v = pivots[j, ch]
            dots = sliding_dots(own, v)
            if normalized:
                dots = np.divide(dots - (mean[ch] - x[ch].mean()) * v.sum(), std[ch], out=np.zeros(n), where=std[ch] > 0)
            else:
                dots = dots + x[ch].mean() * v.sum()
            out[:, ch * p + j] = np.sqrt(np.maximum(rest - 2 * dots + (v * v).sum(), 0))
    return out


def segment_features(x: np.ndarray, q: int, cuts: list[int], with_std: bool, normalized: bool = False) -> np.ndarray:
    """Per window of one channel: mean (and deviation) of each segment, scaled by the root of its length."""
    n = len(x) - q + 1
    if n <= 0:
        return np.zeros((0, (len(cuts) - 1) * (2 if with_std else 1)))
    cols = []
    mean, std = window_stats(x[None], q)
    for a, b in zip(cuts, cuts[1:], strict=False):
        m, s = window_stats(x[None], b - a)
        m, s = m[0, a : a + n], s[0, a : a + n]
        if normalized:
            m = np.divide(m - mean[0], std[0], out=np.zeros(n), where=std[0] > 0)
            s = np.divide(s, std[0], out=np.zeros(n), where=std[0] > 0)
        cols.append(m * np.sqrt(b - a))
        if with_std:
            cols.append(s * np.sqrt(b - a))
    return np.stack(cols, axis=1)


def adaptive_cuts(sample: np.ndarray, parts: int) -> list[int]:
    """Segment borders: the segment with the largest spread inside is halved until there are ``parts``."""
    q = sample.shape[1]
    cuts = [0, q]
    while len(cuts) - 1 < min(parts, q):
        inner = [(float(((sample[:, a:b] - sample[:, a:b].mean(axis=1, keepdims=True)) ** 2).sum()) if b - a > 1 else -1.0, a, b) for a, b in zip(cuts, cuts[1:], strict=False)]
        worst, a, b = max(inner)
        if worst < 0:
            break
        cuts = sorted([*cuts, (a + b) // 2])
    return cuts


def box_gap2(y: np.ndarray, lo: np.ndarray, hi: np.ndarray, how: str = "sum") -> np.ndarray:
    """Squared distance of a point to boxes; ``max``: of the worst dimension only."""
    g = np.maximum(np.maximum(lo - y, y - hi), 0) ** 2
    return g.sum(axis=-1) if how == "sum" else g.max(axis=-1, initial=0.0)


def kmeans(x: np.ndarray, k: int, seed: int = 42, rounds: int = 20) -> np.ndarray:
    """Lloyd's centres of a bounded sample; starts at points far apart."""
    g = np.random.default_rng(seed)
    centres = [x.mean(axis=0)] if k == 1 else [x[int(g.integers(len(x)))]]
    while len(centres) < k:
        d = np.min([((x - c) ** 2).sum(axis=1) for c in centres], axis=0)
        centres.append(x[int(np.argmax(d))])
    c = np.array(centres)
    for _ in range(rounds if k > 1 else 0):
        at = np.argmin(((x[:, None] - c[None]) ** 2).sum(axis=2), axis=1)
        c = np.array([x[at == i].mean(axis=0) if (at == i).any() else c[i] for i in range(k)])
    return c


# --- tiling --------------------------------------------------------------------------------------------------------


def softmax_weights(variances: np.ndarray, how: str = "softmax") -> np.ndarray:
    """Weight of each dimension from its variance over a sample."""
    v = np.asarray(variances, float)
    if not len(v):
        return v
    if how == "uniform":
        return np.full(len(v), 1 / len(v))
    if how == "share":
        return v / v.sum() if v.sum() > 0 else np.full(len(v), 1 / len(v))
    if how == "softmax_std":
        v = v / v.mean() if v.mean() > 0 else v
    e = np.exp(v - v.max())
    return e / e.sum()


def split_counts(weights: np.ndarray, n: float, leaf: float) -> np.ndarray:
    """Slices of each dimension: ceil((n / leaf) ** weight); for equal weights the classic d-th root."""
    ratio = max(1.0, n / leaf)
    return np.array([int(np.ceil(ratio**w - 1e-9)) for w in weights], int)


def _node(d: int, cuts: np.ndarray, children: list):
    """A split; the last entry is the number of leaves below it."""
    return (d, cuts, children, sum(1 if c is None else c[3] for c in children))


def learn_router(sample: np.ndarray, n: float, leaf: float, weights: np.ndarray, layout: str = "str"):
    """Nested splits learned from sample features: (dim, borders, children, leaves below), or None for a leaf.

    ``str``: dimensions in order of weight, each cut in its number of slices at quantiles of the branch; a branch
    that would hold ``leaf`` windows or fewer is a leaf. ``kd``: median of the widest dimension.
    """
    if not len(sample) or not sample.shape[1]:
        return None
    per = n / len(sample)
    counts = split_counts(weights, n, leaf)
    order = np.argsort(-weights, kind="stable")

    def tile(rows: np.ndarray, level: int):
        size = len(rows) * per
        if size <= leaf or level >= len(order) or len(rows) < 2:
            return None
        d = int(order[level])
        k = int(min(counts[d], np.ceil(size / leaf)))
        cuts = np.unique(np.quantile(rows[:, d], np.arange(1, k) / k)) if k > 1 else np.zeros(0)
        if not len(cuts):
            return tile(rows, level + 1)
        at = np.searchsorted(cuts, rows[:, d], side="right")
        return _node(d, cuts, [tile(rows[at == i], level + 1) for i in range(len(cuts) + 1)])

    def halve(rows: np.ndarray):
        if len(rows) * per <= leaf or len(rows) < 2:
            return None
        d = int(np.argmax(rows.max(axis=0) - rows.min(axis=0)))
        cut = float(np.median(rows[:, d]))
        right = rows[:, d] >= cut
        if right.all() or not right.any():
            return None
        return _node(d, np.array([cut]), [halve(rows[~right]), halve(rows[right])])

    return tile(sample, 0) if layout == "str" else halve(sample)


def route(features: np.ndarray, router) -> np.ndarray:
    """Leaf number of every row; leaves are numbered in the router's order."""
    out = np.zeros(len(features), np.int64)

    def go(node, rows: np.ndarray, first: int) -> None:
        if node is None:
            out[rows] = first
            return
        d, cuts, children, _ = node
        at = np.searchsorted(cuts, features[rows, d], side="right")
        order = np.argsort(at, kind="stable")
        ends = np.searchsorted(at[order], np.arange(len(children) + 1))
        for i, child in enumerate(children):
            if ends[i + 1] > ends[i]:
                go(child, rows[order[ends[i] : ends[i + 1]]], first)
            first += 1 if child is None else child[3]

    if len(features):
        go(router, np.arange(len(features)), 0)
    return out


def runs(labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and last position of each run of equal labels."""
    if not len(labels):
        return np.zeros(0, int), np.zeros(0, int)
    cut = np.flatnonzero(np.diff(labels)) + 1
    first = np.concatenate([[0], cut])
    return first, np.concatenate([cut - 1, [len(labels) - 1]])


def split_node(boxes: np.ndarray, strategy: str = "quadratic") -> np.ndarray:
    """Two groups (0/1) for an overflowing leaf's boxes (n, 2, d): quadratic, linear or topological seeds."""
    lo, hi = boxes[:, 0], boxes[:, 1]
    n = len(boxes)
    if n < 2:
        return np.zeros(n, int)
    if strategy == "topological":  # axis of least summed margin, then the cut of least overlap
        best = None
        for d in range(lo.shape[1]):
            order = np.argsort(lo[:, d], kind="stable")
            for k in range(max(1, n * 2 // 5), min(n - 1, n - n * 2 // 5) + 1):
                a, b = order[:k], order[k:]
                ext = [(lo[g].min(axis=0), hi[g].max(axis=0)) for g in (a, b)]
                margin = sum((h - m).sum() for m, h in ext)
                both = np.prod(np.maximum(np.minimum(ext[0][1], ext[1][1]) - np.maximum(ext[0][0], ext[1][0]), 0))
                if best is None or (margin, both) < best[0]:
                    best = (margin, both), b
        out = np.zeros(n, int)
        out[best[1]] = 1
        return out
    if strategy == "linear":
        spread = hi.max(axis=0) - lo.min(axis=0)
        gap = (lo.max(axis=0) - hi.min(axis=0)) / np.where(spread > 0, spread, 1)
        d = int(np.argmax(gap))
        a, b = int(np.argmin(hi[:, d])), int(np.argmax(lo[:, d]))
    else:
        grown = np.log1p(np.maximum(hi[:, None], hi[None]) - np.minimum(lo[:, None], lo[None])).sum(axis=2)
        np.fill_diagonal(grown, -1)
        a, b = map(int, np.unravel_index(np.argmax(grown), grown.shape))
    if a == b:
        b = (a + 1) % n
    out = np.zeros(n, int)
    out[b] = 1
    box = [[lo[a], hi[a]], [lo[b], hi[b]]]
    for i in range(n):
        if i in (a, b):
            continue
        cost = [np.log1p(np.maximum(h, hi[i]) - np.minimum(m, lo[i])).sum() - np.log1p(h - m).sum() for m, h in box]
        g = int(cost[1] < cost[0])
        out[i] = g
        box[g] = [np.minimum(box[g][0], lo[i]), np.maximum(box[g][1], hi[i])]
    return out
