"""Privacy machinery: budgets, noise, ledger, accounting, sketch calibration, shared hash keys."""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass, field

import numpy as np


@dataclass(frozen=True)
class Budget:
    """(eps, delta) split: eps0 for the user count, eps1 for local centers, eps2 (delta2) for membership."""

    eps: float
    delta: float
    parties: int
    b: float = 0.98

    @property
    def eps0(self) -> float:
        return (1.0 - self.b) * self.eps

    @property
    def eps1(self) -> float:
        return self.b * self.eps / (2 * self.parties)

    eps2 = eps1

    @property
    def delta2(self) -> float:
        return self.delta / self.parties


def split(eps: float, delta: float, parties: int, b: float = 0.98, method: str = "pairwise", counted: bool = False) -> Budget:
    """Reports count users for free (each one reports), so they keep nothing back for the count, unless it is
    wanted beforehand (``counted``)."""
    return Budget(eps, delta, parties, 1.0 if method.startswith("reports") and not counted else b)


def laplace(values, sensitivity: float, eps: float, rng: np.random.Generator) -> np.ndarray:
    """Values plus Laplace noise of scale (L1 sensitivity / eps)."""
    values = np.asarray(values, float)
    return values + rng.laplace(0.0, sensitivity / eps, values.shape)


def gaussian_scale(l2: float, eps: float, delta: float) -> float:
    """The least standard deviation that gives (eps, delta) for L2 sensitivity ``l2``, valid for every eps > 0.

    Bisection on the exact privacy curve of Gaussian noise; the classic closed form holds for eps up to 1 only.
    """
    if eps <= 0 or not 0 < delta < 1:
        raise ValueError(f"no Gaussian noise gives eps = {eps}, delta = {delta}")

    def tail(x: float) -> float:
        return 0.5 * math.erfc(-x / math.sqrt(2.0))

    def spent(sd: float) -> float:
        a, b = l2 / (2 * sd), eps * sd / l2
        scaled = math.exp(min(eps, 700.0)) * tail(-a - b)
        return tail(a - b) - scaled

    low, high = 1e-6 * l2, l2
    while spent(high) > delta:
        high *= 2
    for _ in range(200):
        middle = (low + high) / 2
        low, high = (middle, high) if spent(middle) > delta else (low, middle)
    return high


def gaussian(values, l2: float, eps: float, delta: float, rng: np.random.Generator) -> np.ndarray:
    """Values plus Gaussian noise for L2 sensitivity ``l2``."""
    values = np.asarray(values, float)
    return values + rng.normal(0.0, gaussian_scale(l2, eps, delta), values.shape)


class HashedNoise:
    """Stands for a random generator where a run must be repeated by other means (tests, SQL): draw number i is
    the md5 uniform of "tag|i". Not private: whoever knows the tag can take the noise off."""

    def __init__(self, tag: str):
        self.tag, self.drawn = tag, 0

    def _next(self, size) -> np.ndarray:
        shape = () if size is None else (size,) if np.isscalar(size) else tuple(size)
        count = math.prod(shape)
        texts = [f"{self.tag}|{i}".encode() for i in range(self.drawn, self.drawn + count)]
        self.drawn += count
        u = [(int(hashlib.md5(t).hexdigest()[:15], 16) + 1) / float(1 << 60) for t in texts]
        return np.array(u).reshape(shape)

    def uniform(self, low: float = 0.0, high: float = 1.0, size=None) -> np.ndarray:
        return low + (high - low) * self._next(size)

    def laplace(self, loc: float = 0.0, scale: float = 1.0, size=None) -> np.ndarray:
        u = self._next(size)
        return loc + np.where(u < 0.5, scale * np.log(2 * u), -scale * np.log(2 * (1 - u) + 1e-18))


@dataclass
class Ledger:
    """What each release has cost. Sequential releases add; releases on disjoint parts cost their largest."""

    rows: list[tuple[int, str, float, float, str]] = field(default_factory=list)

    SCHEMA = "party int, phase string, eps double, delta double, scope string"

    def charge(self, party: int, phase: str, eps: float, delta: float = 0.0, scope: str = "sequential") -> None:
        self.rows.append((party, phase, float(eps), float(delta), scope))

    def parallel(self, party: int, phase: str, parts: list[tuple[float, float]]) -> None:
        self.charge(party, phase, max(e for e, _ in parts), max(d for _, d in parts), "parallel")

    def total(self) -> tuple[float, float]:
        return sum(r[2] for r in self.rows), sum(r[3] for r in self.rows)


def rdp_compose(costs: list[tuple[float, float]]) -> tuple[float, float]:
    """(order, sum) of Renyi costs that are all given at one order."""
    orders = {nu for nu, _ in costs}
    if len(orders) != 1:
        raise ValueError("Renyi costs compose at one order only")
    return orders.pop(), sum(tau for _, tau in costs)


def rdp_to_dp(order: float, cost: float, delta: float) -> float:
    """eps of the (eps, delta) guarantee that a Renyi cost gives."""
    return cost + math.log(1.0 / delta) / (order - 1.0)


def best_order(eps_row: float, rows: int, delta: float) -> tuple[float, float]:
    """(order, eps) for ``rows`` releases of pure eps_row each; a pure release costs order * eps_row^2 / 2."""
    rho = rows * eps_row**2 / 2
    order = 1.0 + math.sqrt(math.log(1.0 / delta) / rho)
    return order, rdp_to_dp(order, rho * order, delta)


def sketch_epsilon(eps2: float, delta2: float, repeats: int, calibration: str = "published") -> float:
    """Budget of one row of a partition sketch.

    ``published`` is the stated split; ``zcdp`` spends the same (eps2, delta2) through concentrated privacy.
    """
    log = math.log(1.0 / delta2)
    if eps2 > 2 * log:
        raise ValueError(f"eps2 = {eps2} is above 2 ln(1/delta2) = {2 * log:.4g}")
    if calibration == "published":
        return eps2 / (4.0 * math.sqrt(repeats * log))
    if calibration == "zcdp":
        rho = (math.sqrt(log + eps2) - math.sqrt(log)) ** 2
        return math.sqrt(2 * rho / repeats)
    raise ValueError(calibration)


def phantoms(eps_row: float) -> int:
    """Elements added to each sketch so that one user more or less hardly shows."""
    return math.ceil(1.0 / math.expm1(eps_row))


def floor_value(eps_row: float, gamma: float) -> int:
    """The smallest value that a sketch may show."""
    return math.ceil(-math.log(-math.expm1(-eps_row)) / math.log1p(gamma))


@dataclass(frozen=True)
class HashKeys:
    """The parties' common hash keys; the server never gets them."""

    values: tuple[int, ...] = field(repr=False)

    def array(self) -> np.ndarray:
        return np.array(self.values, np.uint64)


def combine(shares: list[bytes], repeats: int, how: str = "xor") -> HashKeys:
    """Keys from one random share of each party, by XOR, sum or concatenation of the shares."""
    if how == "concat":
        seed = b"|".join(shares)
    else:
        size = max(map(len, shares))
        numbers = [int.from_bytes(s.ljust(size, b"\0"), "big") for s in shares]
        total = 0
        for x in numbers:
            total = total ^ x if how == "xor" else (total + x) % (1 << (8 * size))
        seed = total.to_bytes(size, "big")
    digest = [hashlib.sha256(seed + i.to_bytes(4, "big")).digest() for i in range(repeats)]
    return HashKeys(tuple(int.from_bytes(d[:8], "big") for d in digest))


@dataclass(frozen=True)
class SketchParams:
    """Repeats M and base gamma are public; the keys are the parties' own."""

    repeats: int = 4096
    gamma: float = 0.1
    keys: HashKeys | None = field(default=None, repr=False)

    def public(self) -> SketchParams:
        return SketchParams(self.repeats, self.gamma)


def choose_k_local(
    n_hat: float, k: int, parties: int, eps2: float, delta: float, repeats: int, rho: float = 0.649
) -> int:
    """Local cluster count: the larger of k^(1/S) and the smallest k0 whose cells drown in noise.

    A cell is expected to hold n / k0^2 users of two parties; the noise is ``cell_sigma`` with s = 2.
    """
    k0 = 1
    while 2 * cell_sigma(n_hat, n_hat / k0**2, k0, 2, repeats, eps2, delta, rho) < n_hat / k0**2:
        k0 += 1
    root = math.ceil(round(k ** (1.0 / parties), 9))
    return max(k0, root)


def cell_sigma(
    n: float, cell: float, k_local: int, s: int, repeats: int, eps2: float, delta: float, rho: float = 0.649
) -> float:
    """Standard deviation of one estimated cell."""
    read = rho * (n - cell) / math.sqrt(repeats)
    return read + 4 * rho * s * (k_local - 1) * math.sqrt(math.log(1.0 / delta)) / eps2


def fm_sigma(n: float, repeats: int, rho: float = 0.649) -> float:
    """Standard deviation of a plain cardinality read-out."""
    return rho * n / math.sqrt(repeats)


def report_sigma(n: float, eps2: float, parties: int) -> float:
    """Order of the standard deviation of a cell that is decoded from per-user reports."""
    return math.sqrt(n / eps2 ** (2 * parties))


def approximation_factor(beta_private: float = 1.0, beta_central: float = 1.0) -> float:
    """Multiplicative factor of the whole method from its two clusterings' factors."""
    return 2 * beta_private + 4 * beta_central * (1 + beta_private)


def approximation_offset(
    n: float, m: int, k: int, parties: int, repeats: int, eps2: float, delta: float,
    local_offset: float = 0.0, beta_central: float = 1.0, omega: float = 0.1,
) -> float:
    """Order of the additive term (constants unknown): local terms plus the cells' errors."""
    cells = n / math.sqrt(repeats) + parties * (k - 1) * math.sqrt(math.log(1 / delta)) / eps2
    rest = beta_central * m**2 * k ** (1.5 * parties) / math.sqrt(omega) * cells
    return 2 * (beta_central + 1) * parties * local_offset + rest


def bytes_per_party(method: str, k_local: int, m_local: int, n: int, repeats: int = 4096) -> int:
    """Bytes a party sends, at 8 bytes a number."""
    numbers = {
        "sketch": k_local * (m_local + repeats),
        "independence": k_local * (m_local + 1),
        "reports": k_local * m_local + n,
        "exact": k_local * m_local + n,
    }
    return 8 * numbers[method]


def operations(method: str, n: int, parties: int, k_local: int, repeats: int) -> int:
    """Hashes of a party, or steps of the server, as counted in the text."""
    return {
        "party_hashes": n * repeats,
        "server_sketch": repeats * parties * k_local**parties,
        "server_exact": n * parties,
    }[method]
