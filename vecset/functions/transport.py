"""Earth mover's distance between small weighted sets, and bounds of it. Pure numpy; masses are integers."""

from __future__ import annotations

import numpy as np


def _flow(cost: np.ndarray, supply: np.ndarray, demand: np.ndarray) -> np.ndarray:
    """Least-cost integer flow by shortest augmenting paths with potentials, which start from costs that are not negative."""
    cost = cost - min(cost.min(), 0.0)
    n, m = cost.shape
    flow, left, need = np.zeros((n, m), np.int64), supply.astype(np.int64).copy(), demand.astype(np.int64).copy()
    pot_u, pot_v = np.zeros(n), np.zeros(m)
    while left.sum() > 0:
        dist_u, dist_v = np.where(left > 0, 0.0, np.inf), np.full(m, np.inf)
        from_v, from_u = np.full(m, -1), np.full(n, -1)
        done_u, done_v = np.zeros(n, bool), np.zeros(m, bool)
        while True:
            u, v = int(np.argmin(np.where(done_u, np.inf, dist_u))), int(np.argmin(np.where(done_v, np.inf, dist_v)))
            du, dv = np.inf if done_u[u] else dist_u[u], np.inf if done_v[v] else dist_v[v]
            if du == np.inf and dv == np.inf:
                break
            if du <= dv:
                done_u[u] = True
                new = du + np.maximum(cost[u] + pot_u[u] - pot_v, 0)
                better = ~done_v & (new < dist_v - 1e-15)
                dist_v[better], from_v[better] = new[better], u
            else:
                done_v[v] = True
                new = dv + np.maximum(-cost[:, v] - pot_u + pot_v[v], 0)
                better = ~done_u & (flow[:, v] > 0) & (new < dist_u - 1e-15)
                dist_u[better], from_u[better] = new[better], v
        end = int(np.argmin(np.where(need > 0, dist_v, np.inf)))
        far = dist_v[end]
        pot_u += np.minimum(dist_u, far)
        pot_v += np.minimum(dist_v, far)
        path, v = [], end
        while True:
            u = from_v[v]
            path.append((u, v, 1))
            if from_u[u] < 0:
                break
            path.append((u, from_u[u], -1))
            v = from_u[u]
        push = min(left[u], need[end], *[flow[a, b] for a, b, sign in path if sign < 0])
        for a, b, sign in path:
            flow[a, b] += sign * push
        left[u] -= push
        need[end] -= push
    return flow


def emd_plan(cost: np.ndarray, a: np.ndarray | None = None, b: np.ndarray | None = None) -> tuple[float, np.ndarray]:
    """(distance, plan whose entries sum to one). a, b: integer counts; left out: ones."""
    cost = np.asarray(cost, float)
    a = np.ones(cost.shape[0], np.int64) if a is None else np.asarray(a, np.int64)
    b = np.ones(cost.shape[1], np.int64) if b is None else np.asarray(b, np.int64)
    plan = _flow(cost, a * b.sum(), b * a.sum()) / float(a.sum() * b.sum())
    return float((plan * cost).sum()), plan


def emd(cost, a=None, b=None, solver: str = "exact") -> float:
    """exact; relaxed (lower bound: the larger one-sided mean of minima); greedy (upper bound); sinkhorn (close, from above)."""
    cost = np.asarray(cost, float)
    wa = np.ones(cost.shape[0]) if a is None else np.asarray(a, float)
    wb = np.ones(cost.shape[1]) if b is None else np.asarray(b, float)
    wa, wb = wa / wa.sum(), wb / wb.sum()
    if solver == "exact":
        return emd_plan(cost, a, b)[0]
    if solver == "relaxed":
        return float(max((wa * cost.min(axis=1)).sum(), (wb * cost.min(axis=0)).sum()))
    if solver == "greedy":
        ra, rb, out = wa.copy(), wb.copy(), 0.0
        for k in np.argsort(cost, axis=None):
            i, j = divmod(int(k), cost.shape[1])
            t = min(ra[i], rb[j])
            ra[i], rb[j], out = ra[i] - t, rb[j] - t, out + t * cost[i, j]
        return float(out)
    if solver == "sinkhorn":
        above = cost - min(cost.min(), 0.0)
        kernel = np.exp(-above / max(0.02 * above.max(), 1e-9))
        u = np.ones(len(wa))
        for _ in range(500):
            v = wb / np.maximum(kernel.T @ u, 1e-300)
            u = wa / np.maximum(kernel @ v, 1e-300)
        plan = u[:, None] * kernel * v[None, :]
        plan *= np.minimum(wa / np.maximum(plan.sum(axis=1), 1e-300), 1)[:, None]
        plan *= np.minimum(wb / np.maximum(plan.sum(axis=0), 1e-300), 1)[None, :]
        ea, eb = wa - plan.sum(axis=1), wb - plan.sum(axis=0)
        plan += np.outer(ea, eb) / max(ea.sum(), 1e-300) if ea.sum() > 1e-15 else 0
        return float((plan * cost).sum())
    raise ValueError(solver)


def entropic(cost: np.ndarray, a: np.ndarray, b: np.ndarray, share: float = 0.05, rounds: int = 40) -> np.ndarray:
    """Earth mover's distances of many pairs at once, from above: cost (pairs, n, m), weights a (pairs, n) and b (pairs, m) that sum to
    one; places that a pair doesn't have weigh 0. `share` of a pair's largest cost smooths it; the plan is then made to fit its margins.
    Codes in fixed point may be a little longer than one: a pair's negative costs are lifted to zero for the kernel, which keeps its plan."""
    live = (a > 0)[:, :, None] & (b > 0)[:, None, :]
    if not live.all():
        some = cost[np.arange(len(cost)), (a > 0).argmax(axis=1), (b > 0).argmax(axis=1)]
        cost = np.where(live, cost, some[:, None, None])
    return entropic_filled(cost, a, b, share, rounds)


def entropic_filled(cost: np.ndarray, a: np.ndarray, b: np.ndarray, share: float = 0.05, rounds: int = 40, most: float = np.inf, look: int = 12) -> np.ndarray:
    """entropic, where places that weigh 0 have the cost of some place of their pair that doesn't, in the precision of cost. After
    `look` rounds the potentials so far bound each distance from below; a pair whose bound is above `most` keeps that bound and goes no
    further."""
    tiny, spare = (1e-300, 1e-15) if cost.dtype == np.float64 else (1e-37, 1e-9)
    least = np.minimum(cost.min(axis=(1, 2)), 0)
    scale = np.maximum(share * (cost.max(axis=(1, 2)) - least), 1e-9)
    kernel = cost - least[:, None, None]
    kernel /= -scale[:, None, None]
    np.exp(kernel, out=kernel)
    times = lambda u: np.matmul(u[:, None, :], kernel)[:, 0]
    into = lambda v: np.matmul(kernel, v[:, :, None])[:, :, 0]
    u, out, go = (a > 0).astype(cost.dtype), None, None
    for turn in range(rounds):
        v = b / np.maximum(times(u), tiny)
        u = a / np.maximum(into(v), tiny)
        if turn + 1 == look and np.isfinite(most):
            f = scale[:, None] * np.log(np.maximum(u, tiny))
            g = (cost - f[:, :, None]).min(axis=1)
            out = (a * (cost - g[:, None, :]).min(axis=2)).sum(axis=1) + (b * g).sum(axis=1)
            go = np.flatnonzero(out <= most)
            if not len(go):
                return out
            if len(go) < len(out):
                cost, a, b, kernel, u, v = (x[go] for x in (cost, a, b, kernel, u, v))
    u *= np.minimum(a / np.maximum(u * into(v), tiny), 1)
    v *= np.minimum(b / np.maximum(v * times(u), tiny), 1)
    ea, eb = a - u * into(v), b - v * times(u)
    left = ea.sum(axis=1)
    kernel *= cost
    total = (u * into(v)).sum(axis=1)
    rest = (ea * np.matmul(cost, eb[:, :, None])[:, :, 0]).sum(axis=1) / np.maximum(left, tiny)
    total += np.where(left > spare, rest, 0)
    if out is None:
        return total
    out[go] = total
    return out


def mean_vector_bound(x: np.ndarray, y: np.ndarray) -> float:
    """Distance of the means: no more than the earth mover's distance under l2."""
    return float(np.linalg.norm(x.mean(axis=0) - y.mean(axis=0)))
