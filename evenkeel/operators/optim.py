"""Steps from gradients.  Gradients are sums over samples; ``step`` gets them divided by
the number of samples.  Penalties are added here, never encoded."""

from __future__ import annotations

import numpy as np

from evenkeel.functions.losses import L1, L2


class Optimizer:
    #: Whether a wrong gradient now and then makes it unstable.
    needs_exact = False

    def __init__(self, p: int, penalty: L1 | L2 | None = None):
        self.beta, self.t, self.penalty = np.zeros(p), 0, penalty

    def point(self) -> np.ndarray:
        """Where the next gradient is wanted."""
        return self.beta

    def _smooth(self, g: np.ndarray, at: np.ndarray) -> np.ndarray:
        return g + self.penalty.gradient(at) if isinstance(self.penalty, L2) else g

    def step(self, g: np.ndarray) -> np.ndarray:
        self.beta = self._move(self._smooth(np.asarray(g, dtype=float), self.point()))
        self.t += 1
        return self.beta


class GD(Optimizer):
    """Constant rate."""

    def __init__(self, p: int, rate: float, penalty=None):
        super().__init__(p, penalty)
        self.rate = rate

    def _move(self, g):
        return self.beta - self.rate * g


class DecayGD(Optimizer):
    """Rate c1 / (t + c2), as inexact gradients want it."""

    def __init__(self, p: int, c1: float, c2: float, penalty=None):
        super().__init__(p, penalty)
        self.c1, self.c2 = c1, c2

    def _move(self, g):
        return self.beta - self.c1 / (self.t + self.c2) * g


class NAG(Optimizer):
    """Accelerated descent, constant rate, momentum t / (t + 3)."""

    needs_exact = True

    def __init__(self, p: int, rate: float, penalty=None):
        super().__init__(p, penalty)
        self.rate, self._ahead = rate, np.zeros(p)

    def point(self):
        return self._ahead

    def _move(self, g):
        new = self._proximal(self._ahead - self.rate * g)
        self._ahead = new + self.t / (self.t + 3) * (new - self.beta)
        return new

    def _proximal(self, beta):
        return beta


class Prox(Optimizer):
    """Proximal step for an L1 penalty."""

    def __init__(self, p: int, rate: float, l1: float):
        super().__init__(p, L1(l1))
        self.rate = rate

    def _move(self, g):
        return self.penalty.proximal(self.beta - self.rate * g, self.rate)


class AcceleratedProx(NAG):
    def __init__(self, p: int, rate: float, l1: float):
        super().__init__(p, rate, L1(l1))

    def _proximal(self, beta):
        return self.penalty.proximal(beta, self.rate)


class FrankWolfe(Optimizer):
    """Conditional gradient on the L1 ball."""

    def __init__(self, p: int, radius: float):
        super().__init__(p)
        self.radius = radius

    def _move(self, g):
        corner, j = np.zeros_like(g), int(np.abs(g).argmax())
        corner[j] = -self.radius * np.sign(g[j])
        return self.beta + 2 / (self.t + 2) * (corner - self.beta)


class LBFGS(Optimizer):
    """Limited-memory quasi-Newton with a fixed step; differences of gradients have to be
    exact."""

    needs_exact = True

    def __init__(self, p: int, memory: int = 8, rate: float = 1.0, first: float = 1.0, penalty=None):
        super().__init__(p, penalty)
        self.memory, self.rate, self.first, self.pairs, self.last = memory, rate, first, [], None

    def _move(self, g):
        if self.last is not None:
            s, y = self.beta - self.last[0], g - self.last[1]
            if s @ y > 1e-12 * (y @ y):
                self.pairs = [*self.pairs, (s, y, 1 / (s @ y))][-self.memory :]
        q, kept = g.copy(), []
        for s, y, r in reversed(self.pairs):
            a = r * (s @ q)
            kept.append(a)
            q -= a * y
        q *= self.pairs[-1][0] @ self.pairs[-1][1] / (self.pairs[-1][1] @ self.pairs[-1][1]) if self.pairs else self.first
        for (s, y, r), a in zip(self.pairs, reversed(kept), strict=True):
            q += s * (a - r * (y @ q))
        self.last = self.beta.copy(), g.copy()
        return self.beta - self.rate * q
