"""Numpy kernels that work on one sentence, or on a stack of equally long ones."""

from __future__ import annotations

import ctypes
from functools import lru_cache

import numpy as np

SLACK, TINY = 1e-12, 1e-13


def laplacians(adj: np.ndarray, skip: np.ndarray, form: str, self_loop: float = 1.0) -> np.ndarray:
    """Dense Laplacians of a stack: adj (m, n - 1), skip (m, n - 2)."""
    m, n = len(adj), adj.shape[1] + 1
    w = np.zeros((m, n, n))
    i = np.arange(n)
    w[:, i, i] = self_loop
    w[:, i[:-1], i[1:]] = w[:, i[1:], i[:-1]] = adj
    if n > 2:
        w[:, i[:-2], i[2:]] = w[:, i[2:], i[:-2]] = skip
    d = w.sum(2)
    if form == "plain":
        lap = -w
        lap[:, i, i] += d
        return lap
    r = np.where(d > 0, 1 / np.sqrt(np.where(d > 0, d, 1)), 0)
    lap = -w * r[:, :, None] * r[:, None, :]
    lap[:, i, i] += d > 0
    return lap


def count_within(values: np.ndarray, cut) -> np.ndarray:
    return np.maximum(1, (values <= np.asarray(cut)[..., None] * (1 + SLACK) + TINY).sum(-1))


def inertia(adj: np.ndarray, skip: np.ndarray, form: str, self_loop: float, cut: float) -> int:
    """How many eigenvalues are within the cut, from the pivots of the shifted
    banded factorisation: linear in the sentence, no matrix is formed."""
    n = len(adj) + 1
    one, two = np.concatenate((adj, [0.0])), np.concatenate((skip, np.zeros(n - len(skip))))
    d = self_loop + one + np.concatenate(([0.0], adj)) + two + np.concatenate((np.zeros(n - len(skip)), skip))
    if form == "plain":
        l0, l1, l2 = d - self_loop, -one, -two
    else:
        r = np.where(d > 0, 1 / np.sqrt(np.where(d > 0, d, 1)), 0)
        l0 = np.where(d > 0, 1 - self_loop * r * r, 0)
        l1, l2 = -one * r * np.append(r[1:], 0), -two * r * np.append(r[2:], [0, 0])[:n]
    x, k = cut * (1 + SLACK) + TINY, 0
    d1 = d2 = p1 = q1 = q2 = 0.0
    for a, b, c in zip((l0 - x).tolist(), l1.tolist(), l2.tolist()):
        pivot = a - p1 * p1 * d1 - q2 * q2 * d2 or 1e-300
        p1, q1, q2, d1, d2 = (b - p1 * q1 * d1) / pivot, c / pivot, q1, pivot, d1
        k += pivot < 0
    return max(1, k)


def flat_bands(bands: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All items one behind the other: adjacent and skip edges by the symbol where
    they begin (0 where none does), and how many symbols each item has."""
    sizes, gap = np.array([len(adj) + 1 for adj, _ in bands]), np.zeros(2)
    one = np.concatenate([x for adj, _ in bands for x in (adj, gap[:1])])
    two = np.concatenate([x for adj, skip in bands for x in (skip, gap[:len(adj) + 1 - len(skip)])])
    return one, two, sizes


def _behind(x: np.ndarray, by: int) -> np.ndarray:
    return np.concatenate((np.zeros(by), x))[:len(x)]


def block_starts(one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Symbols that no edge ties to one before them."""
    crossed = _behind((one != 0) | (two != 0), 1) + _behind(two != 0, 2)
    return np.flatnonzero(crossed == 0)


def band_rows(one: np.ndarray, two: np.ndarray, form: str, self_loop: float) -> tuple[np.ndarray, np.ndarray]:
    """Laplacians of flat bands as rows of diagonal, first and second band, and the
    degrees with the loop."""
    links = one + _behind(one, 1) + two + _behind(two, 2)
    d = links + self_loop
    if form == "plain":
        return np.stack((links, -one, -two), axis=1), d
    r = np.where(d > 0, 1 / np.sqrt(np.where(d > 0, d, 1)), 0)
    next_ = np.concatenate((r, np.zeros(2)))
    return np.stack((np.where(d > 0, 1 - self_loop * r * r, 0), -one * r * next_[1:-1], -two * r * next_[2:]), axis=1), d


#: Numbers of an array that goes through a recurrence for many matrices at once.
LANES = 1 << 18


def _groups(sizes: np.ndarray, lanes: np.ndarray):
    """Places of matrices of about equal size whose lanes fill an array."""
    order = np.argsort(sizes, kind="stable")
    a = 0
    while a < len(order):
        top = int(np.searchsorted(sizes[order], max(sizes[order[a]] * 1.25, sizes[order[a]] + 4), "right"))
        total = lanes[order[a:top]].cumsum() * sizes[order[a:top]]
        b = a + max(1, int(np.searchsorted(total, LANES, "right")))
        yield order[a:b]
        a = b


def only_zero_within(rows: np.ndarray, starts: np.ndarray, sizes: np.ndarray, cut: float) -> np.ndarray:
    """Whether each matrix has no eigenvalue but its 0 within the cut, by the
    pivots of ``inertia`` for all at once; false within a billionth of the cut,
    where rounding would decide."""
    out, x = np.zeros(len(sizes), bool), cut * (1 + 1e-9) + 1e-12
    for some in _groups(sizes, np.ones(len(sizes), int)):
        m, top = len(some), int(sizes[some].max())
        i = np.arange(top)[:, None]
        inside = i < sizes[some]
        l0, l1, l2 = (np.where(inside, rows[np.minimum(starts[some] + i, len(rows) - 1), j], 0.0) for j in range(3))
        l0 = np.where(inside, l0 - x, 1.0)
        k, (d1, d2, p1, q1, q2) = np.zeros(m, int), np.zeros((5, m))
        for a, b, c in zip(l0, l1, l2):
            pivot = a - p1 * p1 * d1 - q2 * q2 * d2
            pivot[pivot == 0] = 1e-300
            p1, q1, q2, d1, d2 = (b - p1 * q1 * d1) / pivot, c / pivot, q1, pivot, d1
            k += pivot < 0
        out[some] = k <= 1
    return out


def alone_within(bands: list[tuple[np.ndarray, np.ndarray]], form: str, self_loop: float, cut: float) -> np.ndarray:
    """``only_zero_within`` of connected items."""
    one, two, sizes = flat_bands(bands)
    return only_zero_within(band_rows(one, two, form, self_loop)[0], sizes.cumsum() - sizes, sizes, cut)


@lru_cache(1)
def _lapack():
    """Routines of the LAPACK that numpy itself is linked with: a band to three
    diagonals, their eigenvalues; and how many threads it takes.  None where they
    are not found by name."""
    try:
        lib = ctypes.CDLL(np.linalg._umath_linalg.__file__)
        reduce_, values, threads = lib.scipy_dsbtrd_64_, lib.scipy_dsterf_64_, lib.scipy_openblas_set_num_threads64_  # 64-bit integers
    except (AttributeError, OSError):
        return None
    for f, n in ((reduce_, 12), (values, 4)):
        f.argtypes, f.restype = [ctypes.c_void_p] * n, None
    threads.argtypes, threads.restype = [ctypes.c_int], None
    return reduce_, values, threads


def one_thread() -> None:
    """A task has one core: threads of matrix products beside it would mostly wait,
    and waiting takes CPU."""
    if _lapack() is not None:
        _lapack()[2](1)


def low_vectors(rows: np.ndarray, starts: np.ndarray, sizes: np.ndarray, cut: float) -> list[tuple[np.ndarray, np.ndarray] | None]:
    """All eigenvalues, ascending, and orthonormal vectors of those within the cut
    (one at least), of matrices given by ``band_rows``.  No dense matrix is
    decomposed: bands become three diagonals, and vectors come from their two
    factorisations, met where the residual is least, for all matrices at once.  None
    where that is not exact (eigenvalues too near for a vector each) or not found."""
    out: list = [None] * len(sizes)
    if _lapack() is None:
        return out
    area = (sizes * sizes).cumsum()
    first = 0
    while first < len(sizes):  # the reflections of all need not be held
        last = max(first + 1, int(np.searchsorted(area, (area[first - 1] if first else 0) + (1 << 21), "right")))
        out[first:last] = _low_vectors(rows, starts[first:last], sizes[first:last], cut)
        first = last
    return out


def _low_vectors(rows: np.ndarray, starts: np.ndarray, sizes: np.ndarray, cut: float) -> list:
    reduce_, eigenvalues = _lapack()[:2]
    total, at = int(sizes.sum()), np.cumsum(sizes) - sizes
    where = np.repeat(starts - at, sizes) + np.arange(total)
    ab, d, e = np.ascontiguousarray(rows[where]), np.zeros(total), np.zeros(total)
    squares = np.cumsum(sizes * sizes) - sizes * sizes
    q, work = np.empty(int((sizes * sizes).sum())), np.empty(int(sizes.max()))
    n64, two, three, failed = sizes.astype(np.int64), np.array([2]), np.array([3]), np.zeros(1, np.int64)
    letters = ctypes.create_string_buffer(b"VL")
    v_, l_ = ctypes.addressof(letters), ctypes.addressof(letters) + 1
    p_n, p_ab, p_d, p_e, p_q, p_work, p_2, p_3, p_failed = (x.ctypes.data for x in (n64, ab, d, e, q, work, two, three, failed))
    good = np.ones(len(sizes), bool)
    for j, (a, s) in enumerate(zip((at * 8).tolist(), (squares * 8).tolist())):
        n_ = p_n + 8 * j
        reduce_(v_, l_, n_, p_2, p_ab + 3 * a, p_3, p_d + a, p_e + a, p_q + s, n_, p_work, p_failed)
        good[j] = failed[0] == 0
    w, spent = d.copy(), e.copy()
    p_w, p_spent = w.ctypes.data, spent.ctypes.data
    for j, a in enumerate((at * 8).tolist()):
        eigenvalues(p_n + 8 * j, p_w + a, p_spent + a, p_failed)
        good[j] &= failed[0] == 0
    counts = np.maximum(1, np.add.reduceat(w <= cut * (1 + SLACK) + TINY, at))
    scale = 1 + np.maximum.reduceat(np.abs(ab).max(1) if len(ab) else ab, at)
    out: list = [None] * len(sizes)
    for some in _groups(sizes, counts):
        own = np.repeat(some, counts[some])
        ends = counts[some].cumsum()
        rank = np.arange(len(own)) - np.repeat(ends - counts[some], counts[some])
        z, rest = _tridiagonal_vectors(d, e, at[own], sizes[own], w[at[own] + rank])
        exact = rest <= 1e-12 * scale[own]
        for j, b in zip(some.tolist(), ends.tolist()):
            n, k, s = int(sizes[j]), int(counts[j]), int(squares[j])
            own_z = _orthonormal(z[:n, b - k:b]) if good[j] and exact[b - k:b].all() else None
            if own_z is None:
                continue
            out[j] = w[at[j]:at[j] + n], q[s:s + n * n].reshape(n, n).T @ own_z
    return out


@lru_cache
def _upper(n: int) -> np.ndarray:
    """Ones above the diagonal, a half on it."""
    return np.triu(np.ones((n, n)), 1) + np.eye(n) / 2


def _orthonormal(z: np.ndarray) -> np.ndarray | None:
    """Unit columns, each made orthogonal to those before it; None where they are
    nearly dependent."""
    k = z.shape[1]
    while True:
        gram = z.T @ z
        gram.flat[::k + 1] -= 1
        off = max(gram.max(), -gram.min())
        if not off <= 0.3:
            return None
        if off > 1e-3:
            gram.flat[::k + 1] += 1
            try:
                return np.linalg.solve(np.linalg.cholesky(gram), z.T).T
            except np.linalg.LinAlgError:
                return None
        z = z - z @ (gram * _upper(1 << int(k).bit_length())[:k, :k])
        if off <= 1e-8:  # what is left is its square
            return z


def _tridiagonal_vectors(d: np.ndarray, e: np.ndarray, at: np.ndarray, sizes: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit vectors (symbols, lanes) of symmetric matrices of three diagonals for
    their eigenvalues, and residuals: factorised from both ends, met where the
    remainder is least."""
    n = int(sizes.max())
    i = np.arange(n)[:, None]
    inside = i < sizes
    places = np.minimum(at + i, len(d) - 1)
    a = np.where(inside, d[places] - values, 1.0)
    b = np.where(i < sizes - 1, e[places], 0.0)
    square = b * b
    down, up, t = np.empty_like(a), np.empty_like(a), np.empty(len(values))
    down[0], up[n - 1] = a[0] + 1e-100, a[n - 1] + 1e-100  # keeps zeros from being divided by, alters nothing else
    for j in range(1, n):
        np.divide(square[j - 1], down[j - 1], out=t)
        np.subtract(a[j], t, out=t)
        np.add(t, 1e-100, out=down[j])
        np.divide(square[n - 1 - j], up[n - j], out=t)
        np.subtract(a[n - 1 - j], t, out=t)
        np.add(t, 1e-100, out=up[n - 1 - j])
    rest = np.abs(down + up - a)
    rest[~inside] = np.inf
    met = rest.argmin(0)
    lane = np.arange(len(values))
    rest = rest[met, lane]
    np.negative(b, out=b)
    np.divide(b[:-1], up[1:], out=up[1:])
    np.divide(b, down, out=down)
    z = np.zeros_like(a)
    z[met, lane] = 1
    for j in range(int(met.max()) - 1, -1, -1):  # upwards: zero until the place is met
        np.multiply(down[j], z[j + 1], out=t)
        np.add(z[j], t, out=z[j])
    below = np.zeros_like(a)
    below[met, lane] = 1
    for j in range(int(met.min()) + 1, n):
        np.multiply(up[j], below[j - 1], out=t)
        np.add(below[j], t, out=below[j])
    z += below
    z[met, lane] = 1
    length = np.sqrt((z * z).sum(0))
    z /= length
    return z, rest / length


def null_vectors(degrees: np.ndarray, starts: np.ndarray, sizes: np.ndarray, form: str) -> np.ndarray:
    """Unit eigenvectors of the eigenvalue 0 of connected blocks, flat."""
    root = np.ones(len(degrees)) if form == "plain" else np.sqrt(degrees)
    root[starts[sizes == 1]] = 1
    return root / np.repeat(np.sqrt(np.add.reduceat(root * root, starts)), sizes)


def null_vector(adj: np.ndarray, skip: np.ndarray, form: str, self_loop: float) -> np.ndarray:
    """The unit eigenvector of the eigenvalue 0, of symbols that are connected."""
    one, two, sizes = flat_bands([(adj, skip)])
    return null_vectors(band_rows(one, two, form, self_loop)[1], np.zeros(1, int), sizes, form)


def gap_cut(values: np.ndarray) -> float:
    """A cut in the middle of the largest step between neighbouring eigenvalues,
    relative to the larger one; of the first half of the spectrum."""
    v = np.maximum(values, 0)[:max(2, len(values) // 2 + 1)]
    if len(v) < 2:
        return 0.0
    step = np.diff(v) / np.maximum(v[1:], 1e-9)
    k = int(step.argmax())
    return float((v[k] + v[k + 1]) / 2)


def _spread_rows(u: np.ndarray, k: int, rng: np.random.Generator) -> list[int]:
    """k rows, each drawn by its squared distance to those before it."""
    own = (u * u).sum(1)

    def distance(j: int) -> np.ndarray:
        far = own + own[j] - 2 * (u @ u[j])
        return np.where(far > 1e-14, far, 0)  # equal rows, up to rounding

    picked = [int(rng.integers(len(u)))]
    far = distance(picked[0])
    while len(picked) < k:
        total = far.sum()
        if total > 0:
            share = (far / total).cumsum()
            picked.append(int((share / share[-1]).searchsorted(rng.random(), side="right")))
        else:
            picked.append(int(rng.integers(len(u))))
        far = np.minimum(far, distance(picked[-1]))
    return picked


def _lloyd(x: np.ndarray, c: np.ndarray, k: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """Labels and centres of a stack: x (m, n, d), c (m, d, d) of which item j
    uses the first k[j] rows and columns."""
    (m, n, d), live = x.shape, np.arange(len(x))
    out, centres = np.zeros((m, n), int), c.copy()
    unused, labels = np.arange(d)[None] >= k[:, None], np.full((m, n), -1)
    for _ in range(rounds):
        # squared distances up to the rows' own squares, by one matrix product
        own = (c * c).sum(2)
        own[unused] = np.inf
        new = (own[:, None] - 2 * (x @ c.transpose(0, 2, 1))).argmin(2)
        moved = (new != labels).any(1)
        labels = new
        if not moved.any():
            break
        if moved.mean() < 0.6:  # those at rest leave
            rest = ~moved
            out[live[rest]], centres[live[rest]] = labels[rest], c[rest]
            live, x, c, unused, labels = live[moved], x[moved], c[moved], unused[moved], labels[moved]
        member = (labels[:, None] == np.arange(d)[None, :, None]).astype(float)
        size = member.sum(2)
        c = np.where(size[:, :, None] > 0, (member @ x) / np.maximum(size, 1)[:, :, None], c)
    out[live], centres[live] = labels, c
    return out, centres


def _lloyd_one(u: np.ndarray, c: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """The same for one large matrix: after a round only centres whose members
    changed are computed again, and only the distances to them."""
    k, u2 = len(c), 2 * u
    score, labels = (c * c).sum(1) - u2 @ c.T, np.full(len(u), -1)
    for _ in range(rounds):
        new = score.argmin(1)
        moved = np.flatnonzero(new != labels)
        if not len(moved):
            break
        touched = np.zeros(k + 1, bool)  # the last place stands for no label yet
        touched[labels[moved]] = touched[new[moved]] = True
        labels = new
        size = np.bincount(labels, minlength=k)
        some = np.flatnonzero(touched[:k] & (size > 0))
        c[some] = ((labels == some[:, None]).astype(float) @ u) / size[some, None]
        score[:, some] = (c[some] ** 2).sum(1) - u2 @ c[some].T
    return labels, c


#: Rows from which on a matrix is clustered by itself and not in a stack.
ALONE = 64


def kmeans_stack(us: list[np.ndarray], init: str = "even", seeds: list[int] | None = None, rounds: int = 100, starts: int = 3) -> list[np.ndarray]:
    """``kmeans`` of many matrices with equally many rows, each in as many
    clusters as it has columns; narrow ones are padded."""
    if us and len(us[0]) >= ALONE:
        return [kmeans(u, u.shape[1], init, seeds[j] if seeds else 0, rounds, starts) for j, u in enumerate(us)]
    out: list = [None] * len(us)
    order = sorted(range(len(us)), key=lambda j: us[j].shape[1])
    while order:
        n, d = us[order[0]].shape
        step = max(1, (1 << 17) // (n * d))
        part, order = order[:step], order[step:]
        k = np.array([us[j].shape[1] for j in part])
        x = np.zeros((len(part), n, k.max()))
        for i, j in enumerate(part):
            x[i, :, :k[i]] = us[j]
        rngs = [np.random.default_rng(seeds[j] if seeds else 0) for j in part] if init != "even" else []
        least = np.full(len(part), np.inf)
        for _ in range(1 if init == "even" else starts):
            c = np.zeros((len(part), k.max(), k.max()))
            for i, j in enumerate(part):
                rows = np.floor((np.arange(k[i]) + 0.5) * n / k[i]).astype(int) if init == "even" else _spread_rows(us[j], int(k[i]), rngs[i])
                c[i, :k[i], :k[i]] = us[j][rows]
            labels, centres = _lloyd(x, c, k, rounds)
            if init == "even":
                for i, own in zip(part, labels):
                    out[i] = own
                break
            inertia = ((x - np.take_along_axis(centres, labels[:, :, None], 1)) ** 2).sum((1, 2))
            for i in np.flatnonzero(inertia < least - 1e-15):
                out[part[i]], least[i] = labels[i], inertia[i]
    return out


def kmeans(u: np.ndarray, k: int, init: str = "even", seed: int = 0, rounds: int = 100, starts: int = 3) -> np.ndarray:
    """Lloyd's algorithm; centres start at evenly spaced rows, or by
    distance-squared draws (best of some starts).  An empty cluster keeps its
    centre."""
    if init == "even":
        return _lloyd_one(u, u[np.floor((np.arange(k) + 0.5) * len(u) / k).astype(int)], rounds)[0]
    rng, best, least = np.random.default_rng(seed), None, np.inf
    for _ in range(starts):
        labels, c = _lloyd_one(u, u[_spread_rows(u, k, rng)], rounds)
        inertia = ((u - c[labels]) ** 2).sum()
        if inertia < least - 1e-15:
            best, least = labels, inertia
    return best


def contiguous_split(u: np.ndarray, k: int) -> np.ndarray:
    """The split of rows into k runs with least squared distance to run means,
    exactly, by dynamic programming."""
    n = len(u)
    s, q = np.vstack((np.zeros(u.shape[1]), u.cumsum(0))), np.concatenate(([0], (u**2).sum(1).cumsum()))
    size = np.maximum(1, np.arange(n + 1)[None] - np.arange(n + 1)[:, None])
    # squared lengths of all differences of running sums, from their products: n * n numbers whatever k is
    own = (s * s).sum(1)
    cost = (q[None] - q[:, None]) - np.maximum(own[None] + own[:, None] - 2 * (s @ s.T), 0) / size
    return _runs(cost, k, n)


def _runs(cost: np.ndarray, k: int, n: int) -> np.ndarray:
    """Least total of cost[start, end] over k runs that cover 0..n."""
    # rows are ends, so that the least of a row is sought in neighbouring numbers
    cost = np.where(np.arange(n + 1)[:, None] < np.arange(n + 1)[None], cost, np.inf).T.copy()
    best, back, at = cost[:, 0].copy(), np.zeros((k + 1, n + 1), int), np.arange(n - k + 1)
    for j in range(2, k + 1):  # j runs leave k - j symbols at least behind them
        ends, starts = slice(j, n - k + j + 1), slice(j - 1, n - k + j)
        total = best[None, starts] + cost[ends, starts]
        least = total.argmin(1)
        back[j, ends] = least + j - 1
        best[ends] = total[at, least]
    labels, end = np.zeros(n, int), n
    for j in range(k, 0, -1):
        start = back[j, end] if j > 1 else 0
        labels[start:end] = j - 1
        end = start
    return labels


def block_costs(adj: np.ndarray, skip: np.ndarray, objective: str, self_loop: float = 1.0) -> np.ndarray:
    """cost[start, end] of one run of symbols in the ratio or normalised cut."""
    n = len(adj) + 1
    w = -laplacians(np.asarray(adj, float)[None], np.asarray(skip, float)[None], "plain", 0.0)[0]
    np.fill_diagonal(w, 0)
    grid = np.pad(w.cumsum(0).cumsum(1), ((1, 0), (1, 0)))
    vol = np.concatenate(([0], (w.sum(1) + self_loop).cumsum()))
    out = np.full((n + 1, n + 1), np.inf)
    for a in range(n):
        for b in range(a + 1, n + 1):
            inner = grid[b, b] - grid[a, b] - grid[b, a] + grid[a, a]
            crossing = vol[b] - vol[a] - self_loop * (b - a) - inner
            mass = b - a if objective == "ratio" else vol[b] - vol[a]
            out[a, b] = max(0.0, crossing) / mass if mass > 0 else 0.0
    return out


def exact_partition(adj, skip, k: int, objective: str = "ratio", self_loop: float = 1.0) -> tuple[float, np.ndarray]:
    """The best split into k runs for a cut objective, with its value."""
    cost = block_costs(adj, skip, objective, self_loop)
    labels = _runs(cost, k, len(cost) - 1)
    return partition_value(cost, labels), labels


def partition_value(cost: np.ndarray, labels: np.ndarray) -> float:
    edges = np.concatenate(([0], np.flatnonzero(np.diff(labels)) + 1, [len(labels)]))
    return float(sum(cost[a, b] for a, b in zip(edges, edges[1:])))


def likelihood_split(s: str, log_p: dict[str, float], longest: int, unknown: float) -> list[str]:
    """Most likely words; an unknown word costs ``unknown`` for each symbol."""
    best, back = [0.0], [0]
    for end in range(1, len(s) + 1):
        options = ((best[a] + log_p.get(s[a:end], unknown * (end - a)), -a) for a in range(max(0, end - longest), end))
        value, a = max(options)
        best.append(value)
        back.append(-a)
    words, end = [], len(s)
    while end:
        words.append(s[back[end]:end])
        end = back[end]
    return words[::-1]


def longest_match(s: str, words: set[str], longest: int, backward: bool = False) -> list[str]:
    """Greedy longest words from the left, or from the right; one symbol where
    no word fits."""
    out, at = [], len(s) if backward else 0
    while (at > 0) if backward else (at < len(s)):
        top = min(longest, at if backward else len(s) - at)
        for n in range(top, 0, -1):
            w = s[at - n:at] if backward else s[at:at + n]
            if n == 1 or w in words:
                break
        out.append(w)
        at += -n if backward else n
    return out[::-1] if backward else out


_BASE = np.uint64(0x9E3779B97F4A7C15)


def _spread(codes: np.ndarray) -> np.ndarray:
    # odd multiples spread neighbouring characters over all bits
    return (codes + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)


def _code_points(s: str) -> np.ndarray:
    return _spread(np.frombuffer(s.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64))


def _slot(h: np.ndarray, bits: int) -> np.ndarray:
    return ((h ^ (h >> np.uint64(31))) * _BASE) >> np.uint64(64 - bits)


class WordTable:
    """Words with counts as sorted 64-bit hashes: some 20 bytes a word; exact but
    for words of equal hash."""

    def __init__(self, words: list[str] | np.ndarray, counts: np.ndarray):
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        self.longest, self.total = int(sizes.max(initial=1)), float(np.sum(counts)) or 1.0
        points, start = _code_points("".join(words)), np.cumsum(sizes) - sizes
        h = np.zeros(len(sizes), np.uint64)
        for j in range(int(sizes.max(initial=0))):
            some = np.flatnonzero(sizes > j)
            h[some] = h[some] * _BASE + points[start[some] + j]
        order = np.argsort(h, kind="stable")
        self.hashes, self.log_p = h[order], np.log(np.asarray(counts, float)[order] / self.total)
        self.unknown = float(np.log(0.1 / self.total))
        self.bits = max(10, int(len(h) * 16).bit_length())
        self.marks = np.zeros(1 << self.bits, bool)  # most substrings end here
        self.marks[_slot(self.hashes, self.bits)] = True
        self.marks = np.packbits(self.marks)

    def found(self, s: str) -> np.ndarray:
        """(len(s), longest): the place in the table of the word that begins at a
        symbol and has so many symbols, or -1."""
        points, n = _code_points(s), len(s)
        top = min(self.longest, n)
        h, out = np.zeros(n, np.uint64), np.full((n, top), -1, np.int64)
        if not len(self.hashes):
            return out
        every = np.zeros((top, n), np.uint64)
        for j in range(top):
            h = h[:n - j] * _BASE + points[j:]
            every[j, :n - j] = h
        slot = _slot(every, self.bits)
        size, at = np.nonzero((self.marks[slot >> np.uint64(3)] >> (np.uint64(7) - (slot & np.uint64(7))).astype(np.uint8)) & 1)
        size, at = size[at + size < n], at[at + size < n]
        place = np.minimum(np.searchsorted(self.hashes, every[size, at]), len(self.hashes) - 1)
        hit = self.hashes[place] == every[size, at]
        out[at[hit], size[hit]] = place[hit]
        return out

    def inside(self, codes: np.ndarray) -> np.ndarray:
        """Whether a word stands over each pair of neighbours, of code points."""
        points, n = _spread(codes), len(codes)
        begin, h = np.zeros(n, np.int64), points
        for j in range(1, min(self.longest, n) if len(self.hashes) else 0):
            h = h[:n - j] * _BASE + points[j:]
            slot = _slot(h, self.bits)
            at = np.flatnonzero((self.marks[slot >> np.uint64(3)] >> (np.uint64(7) - (slot & np.uint64(7))).astype(np.uint8)) & 1)
            place = np.minimum(np.searchsorted(self.hashes, h[at]), len(self.hashes) - 1)
            at = at[self.hashes[place] == h[at]]
            begin[at] += 1
            begin[at + j] -= 1
        return begin.cumsum()[:-1] > 0

    def likely(self, s: str) -> list[str]:
        """``likelihood_split`` with these words."""
        n, found = len(s), self.found(s)
        top = found.shape[1]
        # by the symbol a word ends behind, the longest first
        cost = np.tile(self.unknown * np.arange(top, 0, -1), (n + 1, 1))
        at, size = np.nonzero(found >= 0)
        cost[at + size + 1, top - 1 - size] = self.log_p[found[at, size]]
        best, back = np.zeros(n + 1), np.zeros(n + 1, int)
        for end in range(1, n + 1):
            a = max(0, end - top)
            options = best[a:end] + cost[end, top - (end - a):]
            j = int(options.argmax())
            best[end], back[end] = options[j], a + j
        words, end = [], n
        while end:
            words.append(s[back[end]:end])
            end = int(back[end])
        return words[::-1]

    def longest_first(self, s: str, backward: bool = False) -> list[str]:
        """``longest_match`` with these words."""
        size = np.ones(len(s) + 1, int)
        at, j = np.nonzero(self.found(s) >= 0)
        np.maximum.at(size, at + j + 1 if backward else at, j + 1)
        out, at = [], len(s) if backward else 0
        while (at > 0) if backward else (at < len(s)):
            n = int(size[at])
            out.append(s[at - n:at] if backward else s[at:at + n])
            at += -n if backward else n
        return out[::-1] if backward else out


def join_numbers_dates(words: list[str]) -> list[str]:
    """Put neighbouring digits, decimal points, percent signs and date marks
    back together."""
    out: list[str] = []
    for w in words:
        last = out[-1] if out else ""
        digit_end, digit = last[-1:].isdigit(), w.isdigit()
        mark_end = len(last) > 1 and last[-1] in ".,/-:" and last[-2].isdigit()
        if (digit and (last.isdigit() or digit_end and last[0].isdigit() or mark_end)) or (digit_end and last[0].isdigit() and (w in "%‰年月日时" or w in ".,/-:")):
            out[-1] = last + w
        else:
            out.append(w)
    # a mark that no digit followed stands alone again
    fixed: list[str] = []
    for w in out:
        if len(w) > 1 and w[-1] in ".,/-:" and w[-2].isdigit():
            fixed += [w[:-1], w[-1]]
        else:
            fixed.append(w)
    return fixed
