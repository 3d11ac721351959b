"""The methods once more, plainly, on dense arrays; for comparison only."""

import numpy as np


def als_row(y, mask, factors, n, i):
    """Row i of mode n by the full normal equations over a dense tensor."""
    rank = factors[0].shape[1]
    g, c = np.zeros((rank, rank)), np.zeros(rank)
    for at in np.argwhere(mask):
        if at[n] == i:
            h = np.ones(rank)
            for k, u in enumerate(factors):
                if k != n:
                    h = h * u[at[k]]
            g += np.outer(h, h)
            c += y[tuple(at)] * h
    return g, c


def objective(y, mask, o, factors, m, l1, l2, l3):
    letters = "abcdefg"[: len(factors)]
    x = np.einsum(",".join(f"{a}r" for a in letters) + "->" + letters, *factors)
    w = factors[-1]
    return (((y - o - x) * mask) ** 2).sum() + l1 * ((w[1:] - w[:-1]) ** 2).sum() + l2 * ((w[m:] - w[:-m]) ** 2).sum() + l3 * np.abs(o).sum()


def step_cost(y, mask, o, factors, w, before, ago, l1, l2):
    letters = "abcdefg"[: len(factors)]
    x = np.einsum(",".join(f"{a}r" for a in letters) + ",r->" + letters, *factors, w)
    return (((y - o - x) * mask) ** 2).sum() + l1 * ((before - w) ** 2).sum() + l2 * ((ago - w) ** 2).sum()
