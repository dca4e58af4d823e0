"""Bits-back coding for models with a latent variable: sample the latent from the state, then code value and latent.

prior is a model over latents; likelihood maps a latent to a model over values; posterior maps a value to a model over latents.
The net cost is the negative evidence lower bound; with the exact posterior that is the marginal rate.
"""

from __future__ import annotations

import math

from .ans import ExactState


def encode(state: ExactState, value: int, prior, likelihood, posterior) -> int:
    """Returns the latent that was drawn."""
    latent = state.sample(posterior(value))
    state.encode(likelihood(latent), value)
    state.encode(prior, latent)
    return latent


def decode(state: ExactState, prior, likelihood, posterior) -> int:
    latent = state.decode(prior)
    value = state.decode(likelihood(latent))
    state.encode(posterior(value), latent)
    return value


def kl(q: list[float], p: list[float]) -> float:
    return sum(a * math.log2(a / b) for a, b in zip(q, p, strict=True) if a > 0)


def negative_elbo(value: int, prior: list[float], likelihood: list[list[float]], posterior: list[float]) -> float:
    """Expected bits for a value: -E log p(value, latent) + E log q(latent)."""
    return sum(q * (math.log2(q) - math.log2(prior[z] * likelihood[z][value])) for z, q in enumerate(posterior) if q > 0)


def marginal(value: int, prior: list[float], likelihood: list[list[float]]) -> float:
    return sum(p * likelihood[z][value] for z, p in enumerate(prior))


def exact_posterior(value: int, prior: list[float], likelihood: list[list[float]]) -> list[float]:
    total = marginal(value, prior, likelihood)
    return [p * likelihood[z][value] / total for z, p in enumerate(prior)]
