"""Plain numpy versions of the solvers, loop by loop, for comparison on small tensors."""

from __future__ import annotations

import numpy as np

P, A, B, C, D = 2_147_483_647, 48_271, 1_583_458_089, 784_588_716, 1_226_874_159


def start(dims, rank, seed=42, zero_first=True):
    out = []
    for n, d in enumerate(dims, 1):
        y = np.array([[(i * A + n * B + k * C + seed * D) % P for k in range(rank)] for i in range(d)], dtype=object)
        out.append((y * (y * y + C) % P / P).astype(float))
    if zero_first:
        out[0] = np.zeros_like(out[0])
    return out


def product(factors, index, columns, skip=None):
    out = np.ones((len(index), len(columns)))
    for n, f in enumerate(factors):
        if n != skip:
            out *= f[index[:, n]][:, columns]
    return out


def predict(factors, index):
    return product(factors, index, list(range(factors[0].shape[1]))).sum(1)


def subset_als(index, x, dims, rank, groups, *, inner=1, lam=0.01, weighted=True, seed=42):
    """`groups`: the lists of columns in the order in which they are solved."""
    factors = start(dims, rank, seed)
    residual = x - predict(factors, index)
    for group in groups:
        back = residual + product(factors, index, group).sum(1)
        for _ in range(inner):
            for n, d in enumerate(dims):
                p = product(factors, index, group, n)
                for i in range(d):
                    mine = index[:, n] == i
                    if not mine.any():
                        factors[n][i, group] = 0
                        continue
                    gram = p[mine].T @ p[mine] + lam * (mine.sum() if weighted else 1) * np.eye(len(group))
                    factors[n][i, group] = np.linalg.solve(gram, p[mine].T @ back[mine])
        residual = back - product(factors, index, group).sum(1)
    return factors


def loss(factors, index, x, lam, weighted):
    error = ((x - predict(factors, index)) ** 2).sum()
    for n, f in enumerate(factors):
        counts = np.bincount(index[:, n], minlength=len(f)) if weighted else np.ones(len(f))
        error += lam * (counts[:, None] * f**2).sum()
    return error


def sgd_pass(index, x, factors, lam, eta):
    for at, value in zip(index, x):
        old = [f[i].copy() for f, i in zip(factors, at)]
        error = value - np.prod(old, axis=0).sum()
        for n, i in enumerate(at):
            other = np.prod([o for m, o in enumerate(old) if m != n], axis=0)
            factors[n][i] = old[n] - 2 * eta * (lam * old[n] - error * other)
