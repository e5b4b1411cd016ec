"""Tensor-train linear algebra on one array: the only numpy linear algebra here.

A train is a list of cores of shape (left rank, mode, right rank); the outer ranks
are 1. Arrays are flat and column-major.
"""

from __future__ import annotations

from math import prod, sqrt

import numpy as np

#: Below this tolerance products of a matrix with itself lose too many digits.
GRAM_LEAST = 1e-6
#: The same where a matrix has up to twice as many columns as rows, or fewer.
GRAM_SQUARE = 1e-4
#: Up to so many rows are cut together.
EARLY_ROWS = 32

Train = list[np.ndarray]


def cut_rank(sigma: np.ndarray, threshold: float) -> int:
    """Fewest leading singular values whose tail has at most this norm; 1 at least."""
    tail = np.sqrt(np.cumsum(sigma[::-1] ** 2))[::-1]
    return max(1, int((tail > threshold).sum()))


def _left_factor(m: np.ndarray, threshold: float, scale: float) -> tuple[np.ndarray, np.ndarray, float]:
    """Orthonormal columns u and u'm with m within the threshold of u u'm, and the square of what is lost."""
    rows, cols = m.shape
    if cols >= rows and threshold > (GRAM_LEAST if cols > 2 * rows else GRAM_SQUARE) * scale:
        value, u = np.linalg.eigh(m @ m.T)
        sigma, u = np.sqrt(np.maximum(value[::-1], 0)), u[:, ::-1]
        if cut_rank(sigma, threshold) == rows:
            return np.eye(rows), m, 0.0
    elif rows > cols and threshold > GRAM_SQUARE * scale:
        value, v = np.linalg.eigh(m.T @ m)
        sigma, v = np.sqrt(np.maximum(value[::-1], 0)), v[:, ::-1]
        r = cut_rank(sigma, threshold)
        if sigma[r - 1] > 1e-3 * sigma[0]:  # else these columns would not be orthonormal to enough digits
            u = m @ (v[:, :r] / sigma[:r])
            sign = np.where(u[np.abs(u).argmax(0), np.arange(r)] < 0, -1.0, 1.0)
            return u * sign, (v[:, :r] * (sigma[:r] * sign)).T, float((sigma[r:] ** 2).sum())
        u, sigma = _by_svd(m)
    elif cols > 2 * rows and threshold > 1e-13 * scale:
        u, sigma, _ = np.linalg.svd(np.linalg.qr(m.T, mode="r").T, full_matrices=False)
    else:
        u, sigma = _by_svd(m)
    r = cut_rank(sigma, threshold)
    u = u[:, :r]
    u = u * np.where(u[np.abs(u).argmax(0), np.arange(r)] < 0, -1.0, 1.0)
    return u, (m.T @ u).T, float((sigma[r:] ** 2).sum())


def _by_svd(m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Left singular vectors and singular values."""
    try:
        return np.linalg.svd(m, full_matrices=False)[:2]
    except np.linalg.LinAlgError:
        q, r = np.linalg.qr(m)
        u, sigma, _ = np.linalg.svd(r, full_matrices=False)
        return q @ u, sigma


def decompose(x: np.ndarray, modes: list[int], tau: float, max_rank: int | None = None) -> tuple[Train, float]:
    """A train within relative Frobenius error tau of x, and the square of the error.

    The budget is shared by the d - 1 cuts; with one mode the train is x itself, and
    zeros give a train of rank 1. With max_rank the error may pass tau; it is returned.
    """
    norm = float(np.linalg.norm(x))
    if norm == 0:
        return [np.zeros((1, n, 1)) for n in modes], 0.0
    threshold = tau * norm / sqrt(max(1, len(modes) - 1))
    rest, rank, lost, cores = np.asarray(x, float), 1, 0.0, []
    early = next((k for k in range(len(modes)) if prod(modes[: k + 1]) > EARLY_ROWS), 0)
    if early > 1 and max_rank is None and threshold > GRAM_SQUARE * norm and prod(modes[:early]) ** 2 < x.size:
        # The first cuts depend on the products of these rows alone, so all of them are made in a small array.
        m = rest.reshape(prod(modes[:early]), -1, order="F")
        value, u = np.linalg.eigh(m @ m.T)
        small = u * np.sqrt(np.maximum(value, 0))
        for n in modes[:early]:
            u, small, out = _left_factor(small.reshape(rank * n, -1, order="F"), threshold, norm)
            lost += out
            cores.append(u.reshape(rank, n, -1, order="F"))
            rank = u.shape[1]
        rest = m if rank == len(m) else (m.T @ rows(cores).T).T
    for n in modes[len(cores) : -1]:
        m = rest.reshape(rank * n, -1, order="F")
        u, rest, out = _left_factor(m, threshold, norm)
        if max_rank is not None and u.shape[1] > max_rank:
            out += float((rest[max_rank:] ** 2).sum())
            u, rest = u[:, :max_rank], rest[:max_rank]
        lost += out
        cores.append(u.reshape(rank, n, -1, order="F"))
        rank = u.shape[1]
    cores.append(rest.reshape(rank, modes[-1], 1, order="F"))
    return cores, lost


def right_orthogonal(cores: Train) -> Train:
    """The same tensor with orthonormal rows in every core but the first; ranks shrink where they can."""
    out, carry = [], np.ones((1, 1))
    for k in range(len(cores) - 1, 0, -1):
        c = np.tensordot(cores[k], carry, (2, 0))
        a, n, b = c.shape
        q, r = np.linalg.qr(c.reshape(a, n * b, order="F").T)
        out.append(q.T.reshape(-1, n, b, order="F"))
        carry = r.T
    return [np.tensordot(cores[0], carry, (2, 0)), *out[::-1]]


def recompress(cores: Train, tau: float, norm: float | None = None) -> tuple[Train, float]:
    """Rounding: a train of smaller ranks within relative error tau, and the square of the error."""
    cores = right_orthogonal(cores)
    norm = float(np.linalg.norm(cores[0])) if norm is None else norm
    if norm == 0:
        return [np.zeros((1, c.shape[1], 1)) for c in cores], 0.0
    threshold, lost, out = tau * norm / sqrt(max(1, len(cores) - 1)), 0.0, []
    for k in range(len(cores) - 1):
        a, n, b = cores[k].shape
        u, rest, gone = _left_factor(cores[k].reshape(a * n, b, order="F"), threshold, norm)
        lost += gone
        out.append(u.reshape(a, n, -1, order="F"))
        cores[k + 1] = np.tensordot(rest, cores[k + 1], (1, 0))
    return [*out, cores[-1]], lost


def rows(cores: Train) -> np.ndarray:
    """All entries of leading cores, flat, for each right rank [rank, entry]: one product of what the first modes and the last ones give."""
    count = np.cumprod([c.shape[1] for c in cores])
    half = int(np.searchsorted(count.astype(float) ** 2, count[-1])) + 1
    first, last = np.ones((1, 1)), np.eye(cores[-1].shape[2])
    for c in cores[:half]:
        first = (c.transpose(2, 1, 0).reshape(-1, c.shape[0]) @ first).reshape(c.shape[2], -1)
    for c in reversed(cores[half:]):
        last = (last @ c.transpose(2, 1, 0).reshape(c.shape[2], -1)).reshape(-1, c.shape[0])
    return (last @ first).reshape(cores[-1].shape[2], -1)


def expand(cores: Train) -> np.ndarray:
    """All entries, flat."""
    return rows(cores)[0]


def distance(cores: Train, x: np.ndarray) -> float:
    """The norm of x less the train, by indices of the last mode, so that no second array of the size of x is made."""
    if len(cores) == 1:
        return float(np.linalg.norm(expand(cores) - x))
    last = cores[-1][:, :, 0]
    head = rows(cores[:-1])
    return sqrt(sum(float(np.linalg.norm(last[:, k] @ head - part)) ** 2 for k, part in enumerate(x.reshape(-1, last.shape[1], order="F").T)))


def entries(cores: Train, index: np.ndarray) -> np.ndarray:
    """Entries at rows of 0-based digits [point, mode], some thousands at a time.

    Points are taken mode by mode in order of their digit, so that each index of a core is one product of matrices.
    """
    out = np.empty(len(index))
    for first in range(0, len(index), 16_384):
        part = index[first : first + 16_384]
        v = np.ones((len(part), 1))
        for k, c in enumerate(cores):
            now = np.empty((len(part), c.shape[2]))
            order = np.argsort(part[:, k], kind="stable")
            cuts = np.searchsorted(part[order, k], np.arange(c.shape[1] + 1))
            for i in np.flatnonzero(np.diff(cuts)):
                at = order[cuts[i] : cuts[i + 1]]
                now[at] = v[at] @ c[:, i, :]
            v = now
        out[first : first + len(part)] = v[:, 0]
    return out


def dot(a: Train, b: Train) -> float:
    m = np.ones((1, 1))
    for x, y in zip(a, b):
        m = np.tensordot(np.tensordot(m, x, (0, 0)), y, ([0, 1], [0, 1]))
    return float(m[0, 0])


def norm(a: Train) -> float:
    return sqrt(max(0.0, dot(a, a)))


def scale(a: Train, c: float) -> Train:
    return [a[0] * c, *a[1:]]


def _blocks(trains: list[Train], grow: int | None = None) -> Train:
    """Block cores of a sum; along ``grow`` each train has index places of its own."""
    d, out = len(trains[0]), []
    for k in range(d):
        own = [t[k] for t in trains]
        left = [1] * len(own) if k == 0 else [c.shape[0] for c in own]
        right = [1] * len(own) if k == d - 1 else [c.shape[2] for c in own]
        n = sum(c.shape[1] for c in own) if k == grow else own[0].shape[1]
        core = np.zeros((1 if k == 0 else sum(left), n, 1 if k == d - 1 else sum(right)))
        a = b = i = 0
        for c, x, y in zip(own, left, right):
            at = slice(i, i + c.shape[1]) if k == grow else slice(None)
            core[a : a + x, at, b : b + y] += c
            a += 0 if k == 0 else x
            b += 0 if k == d - 1 else y
            i += c.shape[1]
        out.append(core)
    return out


def add(a: Train, b: Train) -> Train:
    return _blocks([a, b])


def sub(a: Train, b: Train) -> Train:
    return _blocks([a, scale(b, -1.0)])


def hadamard(a: Train, b: Train) -> Train:
    """Entry by entry. Ranks multiply, but from the left none grows beyond what the indices before it allow."""
    out, carry = [], np.ones((1, 1, 1))
    for k, (x, y) in enumerate(zip(a, b)):
        m = np.stack([np.tensordot(np.tensordot(carry, x[:, i], (1, 0)), y[:, i], (1, 0)) for i in range(x.shape[1])], 1)
        r, (n, p, q) = carry.shape[0], m.shape[-3:]
        m = m.reshape(r * n, p * q, order="F")
        if k == len(a) - 1:
            out.append(m.reshape(r, n, 1, order="F"))
        elif r * n <= p * q:
            out.append(np.eye(r * n).reshape(r, n, r * n, order="F"))
            carry = m.reshape(r * n, p, q, order="F")
        else:
            u, m = np.linalg.qr(m)
            out.append(u.reshape(r, n, -1, order="F"))
            carry = m.reshape(-1, p, q, order="F")
    return out


def concat(trains: list[Train], axis: int = 0) -> Train:
    """One train over the arrays joined along an existing axis."""
    return _blocks(trains, axis)


def stack(trains: list[Train]) -> Train:
    """One train with a new last axis over trains of equal modes."""
    n = len(trains)
    return _blocks([[*t, np.eye(n)[k].reshape(1, n, 1)] for k, t in enumerate(trains)])


def stack_rounded(trains: list[Train], tau: float) -> tuple[Train, float]:
    """Stacked and rounded; the first sweep runs on each train by itself, as their rows share nothing, and block cores are never filled with zeros."""
    if len(trains) == 1:
        return recompress(stack(trains), tau)
    done = [right_orthogonal([*t, np.ones((1, 1, 1))]) for t in trains]
    n = len(done)
    done = [[*t[:-1], t[-1] * np.eye(n)[k].reshape(1, n, 1)] for k, t in enumerate(done)]
    total = sqrt(sum(float(np.linalg.norm(t[0])) ** 2 for t in done))
    modes, lost, out = [c.shape[1] for c in done[0]], 0.0, []
    if total == 0:
        return [np.zeros((1, m, 1)) for m in modes], 0.0
    threshold = tau * total / sqrt(max(1, len(modes) - 1))
    # A short group has one index where others have several; it stands for all of them.
    done = [[np.broadcast_to(c, (c.shape[0], m, c.shape[2])) for c, m in zip(t, modes)] for t in done]
    carry = [np.ones((1, 1))] * n
    for k, m in enumerate(modes[:-1]):
        core = np.concatenate([np.tensordot(c, t[k], (1, 0)) for c, t in zip(carry, done)], 2)
        a, _, b = core.shape
        u, rest, gone = _left_factor(core.reshape(a * m, b, order="F"), threshold, total)
        lost += gone
        out.append(u.reshape(a, m, -1, order="F"))
        carry = np.split(rest, np.cumsum([t[k].shape[2] for t in done])[:-1], 1)
    return [*out, sum(np.tensordot(c, t[-1], (1, 0)) for c, t in zip(carry, done))], lost


def concat_rounded(trains: list[Train], tau: float) -> tuple[Train, float]:
    """Joined along the first axis and rounded. What is behind that axis is stacked, so that block cores are never filled with zeros."""
    carry, done = [np.ones((1, 1))] * len(trains), []
    for k in range(len(trains[0]) - 1, 0, -1):
        core = np.concatenate([np.tensordot(t[k], c, (2, 0)) for t, c in zip(trains, carry)], 0)
        a, n, b = core.shape
        q, r = np.linalg.qr(core.reshape(a, n * b, order="F").T)
        done.append(q.T.reshape(-1, n, b, order="F"))
        carry = np.split(r.T, np.cumsum([t[k].shape[0] for t in trains])[:-1], 0)
    first = np.concatenate([np.tensordot(t[0], c, (2, 0)) for t, c in zip(trains, carry)], 1)
    return recompress([first, *done[::-1]], tau)


def contract(a: Train, weights: dict[int, np.ndarray]) -> Train:
    """Weighted sums over some modes; these disappear. All modes: a single mode of size 1."""
    out, carry = [], None  # None stands for the unit matrix
    for k, c in enumerate(a):
        if k in weights:
            own = np.tensordot(c, np.asarray(weights[k], float), (1, 0))
            carry = own if carry is None else carry @ own
        else:
            out.append(c if carry is None else np.tensordot(carry, c, (1, 0)))
            carry = None
    if not out:
        return [carry.reshape(1, 1, 1)]
    if carry is not None:
        out[-1] = np.tensordot(out[-1], carry, (2, 0))
    return out


def fix(a: Train, at: dict[int, int]) -> Train:
    """The slice at some 0-based indices."""
    return contract(a, {k: np.eye(a[k].shape[1])[i] for k, i in at.items()})


def constant(modes: list[int], c: float = 1.0) -> Train:
    return scale([np.ones((1, n, 1)) for n in modes], c)


def rank_one(vectors: list[np.ndarray]) -> Train:
    return [np.asarray(v, float).reshape(1, -1, 1) for v in vectors]


def delta(modes: list[int], index: list[int], c: float = 1.0) -> Train:
    """c at one 0-based place, else 0."""
    return scale([np.eye(n)[i].reshape(1, n, 1) for n, i in zip(modes, index)], c)


def ranks(a: Train) -> list[int]:
    return [1, *(c.shape[2] for c in a)]


def numel(a: Train) -> int:
    return sum(c.size for c in a)
