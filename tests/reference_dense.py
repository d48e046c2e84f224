"""Plain dense NumPy versions of the methods, for small matrices."""

import numpy as np


def clip(x):
    return np.maximum(x, 0.0)


def largest(x, t, scope="matrix", ties="exact"):
    """Keep the t largest positive entries of the matrix or of each column."""
    if t is None:
        return x
    if scope == "topic":
        return np.column_stack([largest(x[:, [j]], t, "matrix", ties)[:, 0] for j in range(x.shape[1])])
    key = np.rint(x * 1e12)
    flat = [(-key[i, j], i, j) for i in range(x.shape[0]) for j in range(x.shape[1]) if x[i, j] > 0]
    flat.sort()
    if ties == "keep" and len(flat) > t:
        edge = flat[t - 1][0]
        flat = [f for f in flat if f[0] <= edge]
    else:
        flat = flat[:t]
    out = np.zeros_like(x)
    for _, i, j in flat:
        out[i, j] = x[i, j]
    return out


def above(x, tau):
    return x if tau is None else np.where(x >= tau, x, 0.0)


def als(a, u, iters, t_u=None, t_v=None, scope="matrix", ties="exact", tau=(None, None), done=None, shift=0.0):
    """a: terms x documents. Returns (u, v, trace of (residual, error))."""
    trace = []
    for _ in range(iters):
        b = a.T @ u
        if done:
            b = b - done[1] @ (done[0].T @ u)
        v = largest(above(clip((b - shift) @ np.linalg.pinv(u.T @ u)), tau[1]), t_v, scope, ties)
        c = a @ v
        if done:
            c = c - done[0] @ (done[1].T @ v)
        new = largest(above(clip((c - shift) @ np.linalg.pinv(v.T @ v)), tau[0]), t_u, scope, ties)
        trace.append((np.linalg.norm(new - u) / max(np.linalg.norm(new), 1e-300), np.linalg.norm(a - new @ v.T) / np.linalg.norm(a)))
        u = new
    return u, v, trace


def sequential(a, u0, blocks, iters, t_u=None, t_v=None):
    done = None
    for _ in range(blocks):
        u, v, _ = als(a, u0, iters, t_u, t_v, done=done)
        done = (u, v) if done is None else (np.hstack([done[0], u]), np.hstack([done[1], v]))
    return done


def multiplicative(a, u, v, iters):
    for _ in range(iters):
        v = v * (a.T @ u) / np.maximum(v @ (u.T @ u), 1e-12)
        u = u * (a @ v) / np.maximum(u @ (v.T @ v), 1e-12)
    return u, v


def gradient(a, u, v, iters, step=1.0):
    for _ in range(iters):
        g = u.T @ u
        v = clip(v - step / np.linalg.eigvalsh(g).max() * (v @ g - a.T @ u))
        g = v.T @ v
        u = clip(u - step / np.linalg.eigvalsh(g).max() * (u @ g - a @ v))
    return u, v


def accuracy(groups, j):
    d = len(groups)
    if d < 2 or j < 2:
        return 1.0
    same = sum(groups[p] == groups[q] for p in range(d) for q in range(p))
    even = [d // j + (i < d % j) for i in range(j)]
    floor = sum(e * (e - 1) // 2 for e in even)
    return (same - floor) / (d * (d - 1) // 2 - floor)


def norm_ratio(x, l1, l2):
    """The closest non-negative vector with the given sum and norm."""
    n = len(x)
    s = x + (l1 - x.sum()) / n
    zero = np.zeros(n, bool)
    while True:
        m = np.where(zero, 0.0, l1 / (n - zero.sum()))
        d = s - m
        a, b, c = (d * d).sum(), 2 * (m * d).sum(), (m * m).sum() - l2 * l2
        s = m + (-b + np.sqrt(max(0.0, b * b - 4 * a * c))) / (2 * a) * d
        if (s >= -1e-12).all():
            return clip(s)
        zero |= s < 0
        s[zero] = 0.0
        s[~zero] -= (s.sum() - l1) / (~zero).sum()
