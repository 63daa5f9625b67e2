"""Imputation learners: ``fit(x_in, y, seed) -> params`` and ``predict(params, x) -> x_hat``.

``x_in`` and ``x`` are (n, w) with NaN gaps, ``y`` is the truth. Params are dictionaries of arrays. All except the
simple anchors and the Gaussian are stand-ins of the family that the reference names, built on closed-form readouts:
their figures are not those architectures' figures.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

RIDGE = 0.05


def interpolate(x: np.ndarray) -> np.ndarray:
    """Linear interpolation inside each window, flat at the ends, 0 where nothing is observed."""
    out, at = np.zeros_like(x), np.arange(x.shape[1])
    for i, row in enumerate(x):
        seen = ~np.isnan(row)
        if seen.any():
            out[i] = np.interp(at, at[seen], row[seen])
    return out


def ridge(a: np.ndarray, y: np.ndarray, penalty: float = RIDGE) -> np.ndarray:
    """Readout weights from the normal equations, a constant included."""
    a = np.hstack([a, np.ones((len(a), 1))])
    return solve_ridge(a.T @ a, a.T @ y, penalty)


def solve_ridge(gram: np.ndarray, cross: np.ndarray, penalty: float = RIDGE) -> np.ndarray:
    return np.linalg.solve(gram + penalty * max(1e-6, float(np.trace(gram)) / len(gram)) * np.eye(len(gram)), cross)


def _normal(a: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    a = np.hstack([a, np.ones((len(a), 1))])
    return a.T @ a, a.T @ y


def _read(a: np.ndarray, weights: np.ndarray) -> np.ndarray:
    return np.hstack([a, np.ones((len(a), 1))]) @ weights


class Learner:
    """Base: predictions by a ridge readout of ``features``.

    A fit over more windows than fit in memory: ``prepare`` on a sample, ``sums`` of every chunk (complete y, one seed a
    window), added up, and ``from_sums``.
    """

    name = "base"

    def features(self, x: np.ndarray, params: dict) -> np.ndarray:
        raise NotImplementedError

    def prepare(self, x_in: np.ndarray, y: np.ndarray, seed: int) -> dict:
        return {}

    def fit(self, x_in: np.ndarray, y: np.ndarray, seed: int = 0) -> dict:
        params = self.prepare(x_in, y, seed)
        params["readout"] = ridge(self.features(x_in, params), y)
        return params

    def sums(self, params: dict, x_in: np.ndarray, y: np.ndarray, seeds: list[int]) -> dict:
        gram, cross = _normal(self.features(x_in, params), y)
        return {"gram": gram, "cross": cross}

    def from_sums(self, params: dict, sums: dict) -> dict:
        return {**params, "readout": solve_ridge(sums["gram"], sums["cross"])}

    def predict(self, params: dict, x: np.ndarray) -> np.ndarray:
        return _read(self.features(x, params), params["readout"])


class MeanLearner(Learner):
    name = "mean"

    def fit(self, x_in, y, seed=0):
        return {"mean": np.array([np.nanmean(y)])}

    def sums(self, params, x_in, y, seeds):
        return {"n": np.array([y.size]), "total": np.array([y.sum()])}

    def from_sums(self, params, sums):
        return {"mean": sums["total"] / sums["n"]}

    def predict(self, params, x):
        return np.full(x.shape, params["mean"][0])


class WindowMean(Learner):
    name = "window_mean"

    def fit(self, x_in, y, seed=0):
        return {"mean": np.array([np.nanmean(y)])}

    def sums(self, params, x_in, y, seeds):
        return {"n": np.array([y.size]), "total": np.array([y.sum()])}

    def from_sums(self, params, sums):
        return {"mean": sums["total"] / sums["n"]}

    def predict(self, params, x):
        n = (~np.isnan(x)).sum(axis=1)
        m = np.where(n > 0, np.nansum(x, axis=1) / np.maximum(n, 1), params["mean"][0])
        return np.repeat(m[:, None], x.shape[1], axis=1)


class Profile(Learner):
    """The mean of each slot: a cluster's centroid when fitted by cluster."""

    name = "profile"

    def fit(self, x_in, y, seed=0):
        return {"profile": np.nanmean(y, axis=0)}

    def sums(self, params, x_in, y, seeds):
        return {"n": np.array([len(y)]), "total": y.sum(axis=0)}

    def from_sums(self, params, sums):
        return {"profile": sums["total"] / sums["n"]}

    def predict(self, params, x):
        return np.repeat(params["profile"][None], len(x), axis=0)


class Linear(Learner):
    name = "linear"

    def fit(self, x_in, y, seed=0):
        return {"none": np.zeros(1)}

    def sums(self, params, x_in, y, seeds):
        return {}

    def from_sums(self, params, sums):
        return {"none": np.zeros(1)}

    def predict(self, params, x):
        return interpolate(x)


class Carry(Learner):
    """The last observation carried forward (or backward), 0 before the first."""

    name = "locf"
    backward = False

    def fit(self, x_in, y, seed=0):
        return {"none": np.zeros(1)}

    def sums(self, params, x_in, y, seeds):
        return {}

    def from_sums(self, params, sums):
        return {"none": np.zeros(1)}

    def predict(self, params, x):
        x = x[:, ::-1] if self.backward else x
        at = np.where(np.isnan(x), 0, np.arange(1, x.shape[1] + 1)[None])
        at = np.maximum.accumulate(at, axis=1)
        out = np.where(at > 0, np.take_along_axis(np.nan_to_num(x), np.maximum(at - 1, 0), axis=1), 0.0)
        return out[:, ::-1] if self.backward else out


class CarryBack(Carry):
    name = "nocb"
    backward = True


class GaussianConditional(Learner):
    """Mean and shrunk covariance; gaps get their conditional mean. Windows that share a mask share one solve."""

    name = "gaussian"

    def fit(self, x_in, y, seed=0):
        mu = np.nanmean(y, axis=0)
        d = np.nan_to_num(y - mu)
        seen = (~np.isnan(y)).astype(float)
        pairs = np.maximum(seen.T @ seen, 1.0)
        return self.from_moments(mu, d.T @ d / pairs)

    def sums(self, params, x_in, y, seeds):
        return {"n": np.array([float(len(y))]), "total": y.sum(axis=0), "outer": y.T @ y}

    def from_sums(self, params, sums):
        mu = sums["total"] / sums["n"]
        return self.from_moments(mu, sums["outer"] / sums["n"] - np.outer(mu, mu))

    @staticmethod
    def from_moments(mu: np.ndarray, cov: np.ndarray, shrink: float = RIDGE) -> dict:
        cov = (1 - shrink) * cov + shrink * np.diag(np.diag(cov))
        values, vectors = np.linalg.eigh((cov + cov.T) / 2)
        floor = max(1e-9, 1e-6 * float(values.max(initial=0.0)))
        return {"mu": mu, "cov": (vectors * np.maximum(values, floor)) @ vectors.T}

    def predict(self, params, x):
        mu, cov = params["mu"], params["cov"]
        out = np.repeat(mu[None], len(x), axis=0)
        gaps = np.isnan(x)
        lam = RIDGE * float(np.mean(np.diag(cov)))
        for mask in np.unique(gaps, axis=0):
            rows = np.flatnonzero((gaps == mask).all(axis=1))
            seen = ~mask
            if not seen.any():
                continue
            out[np.ix_(rows, seen)] = x[np.ix_(rows, seen)]
            if mask.any():
                gain = np.linalg.solve(cov[np.ix_(seen, seen)] + lam * np.eye(int(seen.sum())), cov[np.ix_(seen, mask)])
                out[np.ix_(rows, mask)] = mu[mask] + (x[np.ix_(rows, seen)] - mu[seen]) @ gain
        return out


class Bidirectional(Learner):
    """Recurrent family: fixed random states run both ways over values and gap flags, with interpolation beside them."""

    name = "bidirectional"
    units = 12
    decay = False

    def prepare(self, x_in, y, seed):
        rng = np.random.default_rng(seed)
        return {"win": rng.normal(0, 0.7, (2, self.units)), "rec": rng.normal(0, 0.6 / np.sqrt(self.units), (self.units, self.units))}

    def features(self, x, params):
        filled = interpolate(x)
        seen = ~np.isnan(x)
        parts = [filled, seen.astype(float)]
        for way in (1, -1):
            h, out, since = np.zeros((len(x), self.units)), [], np.zeros(len(x))
            for j in range(x.shape[1])[::way]:
                now = seen[:, j]
                since = np.where(now, 0.0, since + 1)
                value = np.where(now, np.nan_to_num(x[:, j]), 0.0)
                if self.decay:  # the state fades while nothing is observed
                    h = h * np.exp(-0.5 * since)[:, None]
                h = np.tanh(np.stack([value, now.astype(float)], axis=1) @ params["win"] + h @ params["rec"])
                out.append(h)
            parts.append(np.mean(out, axis=0))
            parts.append(h)
        return np.hstack(parts)


class DecayRecurrent(Bidirectional):
    name = "decay_recurrent"
    decay = True


class MaskedAttention(Learner):
    """Attention family: two passes of kernel attention over positions and values, a slot never attending to itself."""

    name = "attention"

    def prepare(self, x_in, y, seed):
        gaps = np.isnan(x_in)
        best = None
        for width in (0.75, 1.5, 3.0, 6.0):
            e = (self._attend(x_in, width) - y)[gaps]
            loss = float(np.mean(e**2)) if len(e) else 0.0
            if best is None or loss < best[0]:
                best = (loss, width)
        return {"width": np.array([best[1]])}

    @classmethod
    def _attend(cls, x: np.ndarray, width: float, most: int = 1 << 22) -> np.ndarray:
        w = x.shape[1]
        step = max(1, most // (w * w))  # a weight for each pair of slots: some windows at a time
        if len(x) > step:
            return np.vstack([cls._attend(x[i : i + step], width) for i in range(0, len(x), step)])
        at = np.arange(w)
        kernel = np.exp(-((at[:, None] - at[None]) ** 2) / (2 * width**2))
        np.fill_diagonal(kernel, 0.0)
        seen = ~np.isnan(x)
        first = (np.nan_to_num(x) @ kernel.T) / np.maximum(seen @ kernel.T, 1e-9)
        current = np.where(seen, np.nan_to_num(x), first)
        near = np.exp(-((current[:, :, None] - current[:, None, :]) ** 2) / 2) * kernel[None]
        return np.einsum("nij,nj->ni", near, current) / np.maximum(near.sum(axis=2), 1e-9)

    def features(self, x, params):
        second = self._attend(x, float(params["width"][0]))
        return np.hstack([second, np.where(np.isnan(x), second, np.nan_to_num(x)), (~np.isnan(x)).astype(float)])


@dataclass
class Stationarised(Learner):
    """Removes each window's observed mean and spread, lets the inner learner work, and restores them."""

    inner: Learner
    name: str = "stationarised"

    @staticmethod
    def _scale(x):
        n = np.maximum((~np.isnan(x)).sum(axis=1), 1)
        m = np.nansum(x, axis=1) / n
        s = np.sqrt(np.nansum((x - m[:, None]) ** 2, axis=1) / n)
        return m[:, None], np.where(s > 1e-6, s, 1.0)[:, None]

    def fit(self, x_in, y, seed=0):
        m, s = self._scale(x_in)
        return self.inner.fit((x_in - m) / s, (y - m) / s, seed)

    def prepare(self, x_in, y, seed):
        m, s = self._scale(x_in)
        return self.inner.prepare((x_in - m) / s, (y - m) / s, seed)

    def sums(self, params, x_in, y, seeds):
        m, s = self._scale(x_in)
        return self.inner.sums(params, (x_in - m) / s, (y - m) / s, seeds)

    def from_sums(self, params, sums):
        return self.inner.from_sums(params, sums)

    def predict(self, params, x):
        m, s = self._scale(x)
        return self.inner.predict(params, (x - m) / s) * s + m


class LagDecomposed(Learner):
    """Decomposition family: a moving-average trend and the best lag of the remainder's autocorrelation."""

    name = "lag_decomposed"

    def prepare(self, x_in, y, seed):
        rest = y - self._trend(y)
        w = y.shape[1]
        score = [float(np.mean(rest[:, lag:] * rest[:, :-lag])) for lag in range(1, max(2, w // 2 + 1))] if w > 2 else [0.0]
        return {"lag": np.array([1 + int(np.argmax(score))])}

    @staticmethod
    def _trend(x, width=5):
        filled = interpolate(x)
        pad = width // 2
        wide = np.pad(filled, ((0, 0), (pad, pad)), mode="edge")
        return np.stack([wide[:, i : i + filled.shape[1]] for i in range(width)]).mean(axis=0)

    def features(self, x, params):
        trend, lag = self._trend(x), int(params["lag"][0])
        rest = interpolate(x) - trend
        w = x.shape[1]
        near = np.zeros_like(rest)
        near[:, lag:] += rest[:, : w - lag]
        near[:, : w - lag] += rest[:, lag:]
        return np.hstack([trend, near / 2, rest])


class MultiScaleConv(Learner):
    """Convolution family: smoothed copies at several widths."""

    name = "multiscale"

    def features(self, x, params):
        return np.hstack([LagDecomposed._trend(x, width) for width in (1, 3, 5, 7)] + [(~np.isnan(x)).astype(float)])


class SpectralGraph(Learner):
    """Graph family: slots joined by their correlation, gaps rebuilt from the smooth end of the Laplacian's spectrum."""

    name = "spectral_graph"

    def prepare(self, x_in, y, seed):
        with np.errstate(all="ignore"):  # a constant slot, or a single window, has no correlation
            corr = np.nan_to_num(np.corrcoef(y.T)) if len(y) > 1 else np.zeros((y.shape[1], y.shape[1]))
        weight = np.abs(corr) * (1 - np.eye(len(corr)))
        laplacian = np.diag(weight.sum(axis=1)) - corr * (1 - np.eye(len(corr)))
        _, vectors = np.linalg.eigh(laplacian)
        return {"basis": vectors[:, : max(2, len(corr) // 2)], "centre": y.mean(axis=0)}

    def features(self, x, params):
        basis, centre = params["basis"], params["centre"]
        out = np.zeros_like(x)
        for mask in np.unique(np.isnan(x), axis=0):
            rows = np.flatnonzero((np.isnan(x) == mask).all(axis=1))
            b = basis[~mask]
            if len(b):
                pull = np.linalg.solve(b.T @ b + RIDGE * np.eye(b.shape[1]), b.T)
                out[rows] = ((x[np.ix_(rows, ~mask)] - centre[~mask]) @ pull.T) @ basis.T
        return np.hstack([out, (~np.isnan(x)).astype(float)])


class LinearDiffusion(Learner):
    """Diffusion family: a ridge denoiser for each noise level; reverse steps with observed slots clamped, several draws averaged."""

    name = "linear_diffusion"
    levels = (1.0, 0.5, 0.2)
    draws = 4

    def fit(self, x_in, y, seed=0):
        rng = np.random.default_rng(seed)
        seen = ~np.isnan(x_in)
        params = {"seed": np.array([float(seed)])}
        for k, level in enumerate(self.levels):
            noisy = np.where(seen, np.nan_to_num(x_in), y + level * rng.normal(size=y.shape))
            params[f"level{k}"] = ridge(np.hstack([noisy, seen]), y)
        return params

    def prepare(self, x_in, y, seed):
        return {"seed": np.array([float(seed)])}

    def sums(self, params, x_in, y, seeds):
        seen, out = ~np.isnan(x_in), {}
        noise = np.array([np.random.default_rng(s).normal(size=(len(self.levels), y.shape[1])) for s in seeds])
        for k, level in enumerate(self.levels):
            noisy = np.where(seen, np.nan_to_num(x_in), y + level * noise[:, k])
            out[f"gram{k}"], out[f"cross{k}"] = _normal(np.hstack([noisy, seen]), y)
        return out

    def from_sums(self, params, sums):
        return {**params, **{f"level{k}": solve_ridge(sums[f"gram{k}"], sums[f"cross{k}"]) for k in range(len(self.levels))}}

    def predict(self, params, x):
        rng = np.random.default_rng(int(params["seed"][0]))  # the same noise for every window: a guess does not depend on its batch
        seen, total = ~np.isnan(x), np.zeros(x.shape)
        for _ in range(self.draws):
            now = np.where(seen, np.nan_to_num(x), rng.normal(size=(1, x.shape[1])) * self.levels[0])
            for k, level in enumerate(self.levels):
                clean = _read(np.hstack([now, seen]), params[f"level{k}"])
                step = self.levels[k + 1] if k + 1 < len(self.levels) else 0.0
                now = np.where(seen, np.nan_to_num(x), clean + step * rng.normal(size=(1, x.shape[1])))
            total += now
        return total / self.draws


def gaussian_from_moments(rows, totals: list[float], w: int) -> dict:
    """The Gaussian's params from ``pair_moments`` (i, j, n, total; complete windows) and each slot's sum: exact at any size."""
    outer, n = np.zeros((w, w)), 0
    for r in rows:  # w (w + 1) / 2 rows
        outer[r.i, r.j] = outer[r.j, r.i] = r.total
        n = max(n, r.n)
    return LEARNERS["gaussian"].from_sums({}, {"n": np.array([float(n)]), "total": np.array(totals, dtype=float), "outer": outer})


LEARNERS: dict[str, Learner] = {
    m.name: m
    for m in (MeanLearner(), WindowMean(), Profile(), Linear(), Carry(), CarryBack(), GaussianConditional(), Bidirectional(), DecayRecurrent(), MaskedAttention(), Stationarised(MaskedAttention()), LagDecomposed(), MultiScaleConv(), SpectralGraph(), LinearDiffusion())
}
#: Which family stands in for which published architecture of the reference's experiments.
EVALUATED = ("bidirectional", "attention", "stationarised", "spectral_graph", "linear_diffusion")


def pack_params(params: dict) -> dict[str, list[float]]:
    """Arrays as a flat map with their shapes, for a model table."""
    out = {}
    for k, v in params.items():
        out[k] = [float(a) for a in np.asarray(v, dtype=float).reshape(-1)]
        out[f"{k}.shape"] = [float(n) for n in np.shape(v)]
    return out


def unpack_params(flat: dict[str, list[float]]) -> dict:
    return {k: np.array(v).reshape([int(n) for n in flat[f"{k}.shape"]]) for k, v in flat.items() if not k.endswith(".shape")}
