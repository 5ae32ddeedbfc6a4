"""Mixture families: log densities, additive statistics and closed-form solutions.

A family says, for given parameters (a dict of numpy arrays with K leading), how to write the
log joint density of component k as a SQL expression over columns ``x0..`` (and ``y``), which
centred vector ``u`` feeds the statistics, and how the statistics give new parameters. The same
definitions exist in numpy for the Arrow plan, the maintenance sweep and tests.

Statistics of component k: s0 = sum p, s1 = sum p u, s2 = sum p u u' (upper triangle). For Gaussian
families u = x - mean of the entering parameters, so second moments never suffer cancellation; for
regression families u = (design, residual to the entering coefficients).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

LOG_2PI = float(np.log(2 * np.pi))
Params = dict[str, np.ndarray]


def num(v: float) -> str:
    """A DOUBLE literal in SQL."""
    return f"({float(v)!r}D)" if np.isfinite(v) and "e" not in repr(float(v)) else f"CAST('{float(v)!r}' AS DOUBLE)"


def linear_sql(coefficients: np.ndarray, terms: list[str]) -> str:
    return "(" + " + ".join(f"{num(c)} * {t}" if t != "1" else num(c) for c, t in zip(coefficients, terms, strict=True)) + ")"


class EmptyComponentError(ValueError):
    """A component lost all its mass and the policy is to stop."""


@dataclass
class Family:
    """``floor``: least variance; ``ridge``: added to the diagonal of covariances and normal matrices;
    ``on_empty``: ``keep`` the old component, ``reseed`` it at the heaviest component's place, or ``error``."""

    d: int
    floor: float = 1e-9
    ridge: float = 0.0
    on_empty: str = "keep"
    has_y = False

    @property
    def columns(self) -> list[str]:
        return [f"x{j}" for j in range(self.d)] + (["y"] if self.has_y else [])

    def k(self, params: Params) -> int:
        return len(params["var" if self.has_y else "weight"])

    # statistics layout ------------------------------------------------------------------

    def pairs(self) -> list[tuple[int, int]]:
        q = self.q()
        return [(i, j) for i in range(q) for j in range(i, q)]

    def width(self) -> int:
        """Statistics of one component."""
        return 1 + self.q() + len(self.pairs())

    def unpack(self, block: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        q = self.q()
        s2 = np.zeros((q, q))
        for v, (i, j) in zip(block[1 + q :], self.pairs(), strict=True):
            s2[i, j] = s2[j, i] = v
        return float(block[0]), block[1 : 1 + q], s2

    def extra_sql(self, params: Params) -> list[str]:
        return []

    def np_extra(self, x: np.ndarray, p: np.ndarray, params: Params) -> np.ndarray:
        return np.zeros(0)

    def np_stats(self, x: np.ndarray, params: Params, weight: np.ndarray | None = None) -> tuple[float, float, np.ndarray]:
        """(n, log-likelihood, flat statistics) of a block of rows."""
        joint = self.np_log_joint(x, params)
        top = joint.max(1, keepdims=True)
        lse = top[:, 0] + np.log(np.exp(joint - top).sum(1))
        p = np.exp(joint - lse[:, None])
        if weight is not None:
            p = p * weight[:, None]
        parts = []
        rows, cols = np.array(self.pairs()).T
        for k in range(joint.shape[1]):
            u = self.np_u(x, params, k)
            second = (u * p[:, k : k + 1]).T @ u
            parts.append(np.concatenate([[p[:, k].sum()], p[:, k] @ u, second[rows, cols]]))
        flat = np.concatenate([*parts, self.np_extra(x, p, params)])
        return float(len(x)), float(lse.sum()), flat

    def solve(self, n: float, flat: np.ndarray, params: Params) -> Params:
        raise NotImplementedError


@dataclass
class Gaussian(Family):
    """Gaussian mixture. ``cov``: full, diag, spherical or tied."""

    cov: str = "full"

    def q(self) -> int:
        return self.d

    def pairs(self) -> list[tuple[int, int]]:
        if self.cov in ("diag", "spherical"):
            return [(i, i) for i in range(self.d)]
        return super().pairs()

    def _whitening(self, params: Params, k: int) -> tuple[np.ndarray, float]:
        low = np.linalg.inv(np.linalg.cholesky(params["sigma"][k]))
        return low, float(np.log(np.diag(low)).sum()) - 0.5 * self.d * LOG_2PI

    def log_joint_sql(self, params: Params, k: int) -> str:
        low, const = self._whitening(params, k)
        u = self.u_sql(params, k)
        squares = []
        for i in range(self.d):
            z = " + ".join(f"{num(low[i, j])} * {u[j]}" for j in range(i + 1) if low[i, j] != 0 or i == j)
            squares.append(f"({z}) * ({z})" if i == 0 or self.cov in ("diag", "spherical") else f"power({z}, 2)")
        with np.errstate(divide="ignore"):
            start = np.log(params["weight"][k]) + const
        return f"{num(start)} - 0.5D * ({' + '.join(squares)})"

    def u_sql(self, params: Params, k: int) -> list[str]:
        return [f"(x{j} - {num(params['mu'][k, j])})" for j in range(self.d)]

    def np_log_joint(self, x: np.ndarray, params: Params) -> np.ndarray:
        out = np.empty((len(x), self.k(params)))
        for k in range(out.shape[1]):
            low, const = self._whitening(params, k)
            z = (x[:, : self.d] - params["mu"][k]) @ low.T
            with np.errstate(divide="ignore"):
                out[:, k] = np.log(params["weight"][k]) + const - 0.5 * (z * z).sum(1)
        return out

    def np_u(self, x: np.ndarray, params: Params, k: int) -> np.ndarray:
        return x[:, : self.d] - params["mu"][k]

    def from_stats(self, n: float, blocks: list[tuple[float, np.ndarray, np.ndarray]], params: Params) -> Params:
        """Parameters from (s0, s1, s2) about the entering means: weight s0 / n, mean c + s1 / s0, covariance s2 / s0 - (s1 / s0)(s1 / s0)'."""
        weight, mu, sigma = [], [], []
        heaviest = max(range(len(blocks)), key=lambda k: blocks[k][0])
        for k, (s0, s1, s2) in enumerate(blocks):
            if s0 <= 1e-12 * max(n, 1):
                if self.on_empty == "error":
                    raise EmptyComponentError(f"component {k} is empty")
                like = heaviest if self.on_empty == "reseed" else k
                step = np.sqrt(np.diag(params["sigma"][like])) if self.on_empty == "reseed" else 0.0
                weight.append(s0 / n if self.on_empty == "keep" else 1.0 / n)
                mu.append(params["mu"][like] + step)
                sigma.append(params["sigma"][like])
                continue
            shift = s1 / s0
            weight.append(s0 / n)
            mu.append(params["mu"][k] + shift)
            sigma.append(s2 / s0 - np.outer(shift, shift))
        sigma = np.array(sigma)
        if self.cov == "tied":
            sigma = np.repeat((np.array(weight)[:, None, None] * sigma).sum(0, keepdims=True) / sum(weight), len(weight), 0)
        if self.cov == "spherical":
            sigma = np.array([np.eye(self.d) * np.trace(s) / self.d for s in sigma])
        if self.cov == "diag":
            sigma = np.array([np.diag(np.diag(s)) for s in sigma])
        place = np.arange(self.d)
        sigma[:, place, place] = np.maximum(sigma[:, place, place] + self.ridge, self.floor)
        return {"weight": np.array(weight), "mu": np.array(mu), "sigma": sigma}

    def solve(self, n: float, flat: np.ndarray, params: Params) -> Params:
        width = self.width()
        return self.from_stats(n, [self.unpack(flat[k * width : (k + 1) * width]) for k in range(self.k(params))], params)

    def rows(self, params: Params) -> list[tuple]:
        return [(k + 1, float(w), [float(v) for v in m], [[float(v) for v in r] for r in s]) for k, (w, m, s) in enumerate(zip(params["weight"], params["mu"], params["sigma"], strict=True))]

    schema = "comp int, weight double, mu array<double>, sigma array<array<double>>"

    def from_rows(self, rows: list) -> Params:
        rows = sorted(rows, key=lambda r: r["comp"])
        return {"weight": np.array([r["weight"] for r in rows]), "mu": np.array([r["mu"] for r in rows]), "sigma": np.array([r["sigma"] for r in rows])}


def gaussian1d(weight: list[float], mu: list[float], sd: list[float]) -> Params:
    """Parameters of a one-dimensional Gaussian mixture, spread given as standard deviations."""
    return {"weight": np.array(weight, float), "mu": np.array(mu, float)[:, None], "sigma": (np.array(sd, float) ** 2)[:, None, None]}


@dataclass
class LinearMixture(Family):
    """Mixture of linear regressions: p(y | x) = sum of weight_k N(y; x'beta_k, var_k)."""

    intercept: bool = True
    has_y = True

    def terms(self) -> list[str]:
        return [f"x{j}" for j in range(self.d)] + (["1"] if self.intercept else [])

    def design(self, x: np.ndarray) -> np.ndarray:
        return np.column_stack([x[:, : self.d], np.ones(len(x))]) if self.intercept else x[:, : self.d]

    def m(self) -> int:
        return self.d + self.intercept

    def q(self) -> int:
        return self.m() + 1

    def log_weight_sql(self, params: Params, k: int) -> str:
        return num(float(np.log(params["weight"][k])))

    def np_log_weight(self, design: np.ndarray, params: Params) -> np.ndarray:
        return np.log(params["weight"])[None, :]

    def residual_sql(self, params: Params, k: int) -> str:
        return f"(y - {linear_sql(params['beta'][k], self.terms())})"

    def log_joint_sql(self, params: Params, k: int) -> str:
        var = params["var"][k]
        r = self.residual_sql(params, k)
        return f"{self.log_weight_sql(params, k)} + {num(-0.5 * (LOG_2PI + np.log(var)))} - {r} * {r} * {num(0.5 / var)}"

    def u_sql(self, params: Params, k: int) -> list[str]:
        return [t if t != "1" else "1D" for t in self.terms()] + [self.residual_sql(params, k)]

    def np_log_joint(self, x: np.ndarray, params: Params) -> np.ndarray:
        g = self.design(x)
        r = x[:, self.d : self.d + 1] - g @ params["beta"].T
        return self.np_log_weight(g, params) - 0.5 * (LOG_2PI + np.log(params["var"])) - 0.5 * r * r / params["var"]

    def np_u(self, x: np.ndarray, params: Params, k: int) -> np.ndarray:
        g = self.design(x)
        return np.column_stack([g, x[:, self.d] - g @ params["beta"][k]])

    def _experts(self, n: float, flat: np.ndarray, params: Params) -> tuple[list[float], np.ndarray, np.ndarray]:
        mass, beta, var = [], [], []
        width, m = self.width(), self.m()
        for k in range(self.k(params)):
            s0, _, s2 = self.unpack(flat[k * width : (k + 1) * width])
            mass.append(s0)
            if s0 <= 1e-12 * max(n, 1):
                if self.on_empty == "error":
                    raise EmptyComponentError(f"component {k} is empty")
                beta.append(params["beta"][k])
                var.append(params["var"][k])
                continue
            sxx, sxr, srr = s2[:m, :m] + self.ridge * np.eye(m), s2[:m, m], s2[m, m]
            step = np.linalg.lstsq(sxx, sxr, rcond=None)[0]
            beta.append(params["beta"][k] + step)
            var.append(max((srr - sxr @ step) / s0, self.floor))
        return mass, np.array(beta), np.array(var)

    def solve(self, n: float, flat: np.ndarray, params: Params) -> Params:
        mass, beta, var = self._experts(n, flat, params)
        return {"weight": np.maximum(np.array(mass) / n, 1e-300), "beta": beta, "var": var}

    schema = "comp int, weight double, beta array<double>, sd double"

    def rows(self, params: Params) -> list[tuple]:
        return [(k + 1, float(w), [float(v) for v in b], float(np.sqrt(s))) for k, (w, b, s) in enumerate(zip(params["weight"], params["beta"], params["var"], strict=True))]

    def from_rows(self, rows: list) -> Params:
        rows = sorted(rows, key=lambda r: r["comp"])
        return {"weight": np.array([r["weight"] for r in rows]), "beta": np.array([r["beta"] for r in rows]), "var": np.array([r["sd"] for r in rows]) ** 2}

    def prediction_sql(self, params: Params) -> str:
        return " + ".join(f"{num(w)} * {linear_sql(b, self.terms())}" for w, b in zip(params["weight"], params["beta"], strict=True))


@dataclass
class ExpertMixture(LinearMixture):
    """Mixture of experts: the weights are a softmax gate of x.

    ``gate``: ``ls`` solves one least-squares system per round towards centred log responsibilities
    (softmax is invariant to shifts; responsibilities are floored at ``gate_floor``); ``newton1`` takes
    one Newton step on the gate's likelihood. Several Newton steps per round (``irls``) are driven by
    the fitting loop, which repeats the gate pass with the responsibilities held.
    """

    gate: str = "ls"
    gate_floor: float = 1e-6

    def k(self, params: Params) -> int:
        return len(params["var"])

    def _gates(self, design: np.ndarray, params: Params) -> np.ndarray:
        a = design @ params["theta"].T
        top = a.max(1, keepdims=True)
        return a - top - np.log(np.exp(a - top).sum(1, keepdims=True))

    def gate_sql(self, params: Params) -> list[str]:
        return [linear_sql(t, self.terms()) for t in params["theta"]]

    def log_weight_sql(self, params: Params, k: int) -> str:
        a = self.gate_sql(params)
        top = f"greatest({', '.join(a)})" if len(a) > 1 else a[0]
        return f"({a[k]} - {top} - ln({' + '.join(f'exp({v} - {top})' for v in a)}))"

    def np_log_weight(self, design: np.ndarray, params: Params) -> np.ndarray:
        return self._gates(design, params)

    def _gate_pairs(self) -> list[tuple[int, int]]:
        m = self.m()
        return [(i, j) for i in range(m) for j in range(i, m)]

    def extra_sql(self, params: Params) -> list[str]:
        terms = [t if t != "1" else "1D" for t in self.terms()]
        n_comp = self.k(params)
        if self.gate == "ls":
            out = [f"{terms[i]} * {terms[j]}" for i, j in self._gate_pairs()]
            logs = [f"ln(greatest(p{k}, {num(self.gate_floor)}))" for k in range(n_comp)]
            mean = f"(({' + '.join(logs)}) / {num(n_comp)})"
            return out + [f"{t} * ({logs[k]} - {mean})" for k in range(n_comp) for t in terms]
        g = [f"exp({self.log_weight_sql(params, k)})" for k in range(n_comp)]
        out = [f"{t} * (p{k} - {g[k]})" for k in range(n_comp) for t in terms]
        for a in range(n_comp):
            for b in range(a, n_comp):
                w = f"{g[a]} * ({'1D - ' + g[a] if a == b else '-' + g[b]})"
                out += [f"{w} * {terms[i]} * {terms[j]}" for i, j in self._gate_pairs()]
        return out

    def np_extra(self, x: np.ndarray, p: np.ndarray, params: Params) -> np.ndarray:
        design = self.design(x)
        rows, cols = np.array(self._gate_pairs()).T
        n_comp = p.shape[1]
        if self.gate == "ls":
            logs = np.log(np.maximum(p, self.gate_floor))
            target = logs - logs.mean(1, keepdims=True)
            return np.concatenate([(design.T @ design)[rows, cols], (target.T @ design).ravel()])
        g = np.exp(self._gates(design, params))
        out = [((p - g).T @ design).ravel()]
        for a in range(n_comp):
            for b in range(a, n_comp):
                w = g[:, a] * ((a == b) - g[:, b])
                out.append(((design * w[:, None]).T @ design)[rows, cols])
        return np.concatenate(out)

    def solve(self, n: float, flat: np.ndarray, params: Params) -> Params:
        n_comp, m = self.k(params), self.m()
        base = self.width() * n_comp
        _, beta, var = self._experts(n, flat, params)
        extra = flat[base:]
        pairs = self._gate_pairs()

        def square(v: np.ndarray) -> np.ndarray:
            s = np.zeros((m, m))
            for e, (i, j) in zip(v, pairs, strict=True):
                s[i, j] = s[j, i] = e
            return s

        if self.gate == "ls":
            sxx = square(extra[: len(pairs)]) + self.ridge * np.eye(m)
            theta = np.array([np.linalg.lstsq(sxx, extra[len(pairs) + k * m : len(pairs) + (k + 1) * m], rcond=None)[0] for k in range(n_comp)])
        else:
            gradient = extra[: n_comp * m]
            hessian = np.zeros((n_comp * m, n_comp * m))
            at = n_comp * m
            for a in range(n_comp):
                for b in range(a, n_comp):
                    block = square(extra[at : at + len(pairs)])
                    at += len(pairs)
                    hessian[a * m : (a + 1) * m, b * m : (b + 1) * m] = hessian[b * m : (b + 1) * m, a * m : (a + 1) * m] = block
            # the Hessian is singular along equal shifts of all gates: a small ridge picks the centred step
            step = np.linalg.solve(hessian + (self.ridge + 1e-6 * max(n, 1)) * np.eye(len(hessian)), gradient)
            theta = params["theta"] + step.reshape(n_comp, m)
        theta = theta - theta.mean(0, keepdims=True)
        return {"theta": theta, "beta": beta, "var": var}

    schema = "comp int, theta array<double>, beta array<double>, sd double"

    def rows(self, params: Params) -> list[tuple]:
        return [(k + 1, [float(v) for v in t], [float(v) for v in b], float(np.sqrt(s))) for k, (t, b, s) in enumerate(zip(params["theta"], params["beta"], params["var"], strict=True))]

    def from_rows(self, rows: list) -> Params:
        rows = sorted(rows, key=lambda r: r["comp"])
        return {"theta": np.array([r["theta"] for r in rows]), "beta": np.array([r["beta"] for r in rows]), "var": np.array([r["sd"] for r in rows]) ** 2}

    def prediction_sql(self, params: Params) -> str:
        return " + ".join(f"exp({self.log_weight_sql(params, k)}) * {linear_sql(params['beta'][k], self.terms())}" for k in range(self.k(params)))
