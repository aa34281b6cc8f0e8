"""Settings of a profiling run."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class ProfilerConfig:
    """``communities`` and ``topics`` are the model's sizes; priors follow the usual rule (50 over the dimension, 0.1 for words) unless given.

    link_topic: whose topic a diffusion link carries, the diffuser's (``source``) or the diffused document's (``target``).
    popularity: ``raw`` counts, ``log1p`` of them, or the ``share`` of a topic among a time bin's documents.
    factors: which parts of the diffusion score are used, of ``community``, ``topic`` and ``individual``.
    diffusion_kind: ``profile`` (the three factors) or ``similarity`` (as friendship links).
    pg: ``mean``, ``exact`` or ``series`` values of the augmentation variables.
    draw: ``gumbel``, ``inverse`` or ``argmax``.
    use_text: whether words and topics weigh on communities (off for detection from links alone); use_topics: whether topics are drawn at all.
    burnin: sweeps after which counts are averaged for the estimates; the last ones are taken where there are no more sweeps.
    nu_fit: ``gd`` gradient steps, or ``glr`` a generalised linear regression to convergence, for the weights of the individual factor.
    blocks: sub-sweeps; only every blocks-th document of a user changes at once.
    """

    communities: int = 6
    topics: int = 8
    alpha: float | None = None
    rho: float | None = None
    beta: float = 0.1
    sweeps: int = 10
    nu_steps: int = 10
    nu_rate: float = 0.5
    blocks: int = 4
    seed: int = 7
    link_topic: str = "source"
    popularity: str = "share"
    factors: tuple[str, ...] = ("community", "topic", "individual")
    diffusion_kind: str = "profile"
    eta_norm: str = "per_community"
    pg: str = "mean"
    draw: str = "gumbel"
    use_friends: bool = True
    use_diffusion: bool = True
    freeze_communities: bool = False
    use_text: bool = True
    use_topics: bool = True
    burnin: int = 1_000_000
    nu_fit: str = "gd"

    @property
    def topic_prior(self) -> float:
        return 50.0 / self.topics if self.alpha is None else self.alpha

    @property
    def community_prior(self) -> float:
        return 50.0 / self.communities if self.rho is None else self.rho
