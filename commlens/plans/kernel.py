"""The sampler over documents at hand: one document after another, on counters that are current.

It serves three plans: the serial sampler over a whole small graph, the chunks of the segmented schedule (users of the chunk live, all
others as they were when the sweep began), and the folds of an experiment, each fitted in a task of its own.

A document's candidates are scored by the counts without the document, times the factor of each of its user's friendship links and each
diffusion link that it is an end of; a factor is exp((x - a x^2) / 2) with the link's augmentation variable a.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from commlens.config import ProfilerConfig
from commlens.functions.augmentation import KeyedRandom, pg_exact, pg_mean_of, pg_series


@dataclass
class Ends:
    """Link ends of one document: the other end's user (a row of memberships), whether the document is the link's source, time bin, individual score and
    augmentation variable; of links it is the target of, also the source's topic, and its place where it is among the documents at hand, else -1."""

    other: np.ndarray
    source: np.ndarray
    tbin: np.ndarray
    own: np.ndarray
    aug: np.ndarray
    topic: np.ndarray
    doc: np.ndarray


@dataclass
class State:
    """``tw`` (topics, words) and ``nz`` their sums over all words; ``ct`` (communities, topics); ``uc`` counts of the users at hand, who are
    the first rows of ``pi`` (users, communities), shares of all users met; ``tensor`` (topics, c, c2), ``pop`` (topics, bins)."""

    tw: np.ndarray
    nz: np.ndarray
    ct: np.ndarray
    uc: np.ndarray
    pi: np.ndarray
    tensor: np.ndarray
    pop: np.ndarray
    n_words: int
    friends: dict[int, tuple[np.ndarray, np.ndarray]] = field(default_factory=dict)
    moments: dict[int, tuple[np.ndarray, np.ndarray]] = field(default_factory=dict)
    ends: dict[int, Ends] = field(default_factory=dict)
    terms: dict[int, tuple[np.ndarray, np.ndarray]] = field(default_factory=dict)


def log_factor(x: np.ndarray, a: np.ndarray) -> np.ndarray:
    return (x - a * x * x) / 2.0


class Kernel:
    def __init__(self, cfg: ProfilerConfig, state: State, user: np.ndarray, c: np.ndarray, z: np.ndarray, words: list[np.ndarray], counts: list[np.ndarray]) -> None:
        self.cfg, self.s = cfg, state
        self.user, self.c, self.z, self.words, self.counts = user, c.copy(), z.copy(), words, counts
        self.size = np.array([int(k.sum()) for k in counts])
        self.profile = cfg.use_diffusion and cfg.diffusion_kind == "profile" and bool(cfg.factors)

    def topic_scores(self, i: int) -> np.ndarray:
        """Log weights of the topics of document i, which is out of ``tw`` and ``nz`` and, of ``ct``, too."""
        cfg, s = self.cfg, self.s
        out = np.log(s.ct[self.c[i]] + cfg.topic_prior)
        if cfg.use_text:
            out = out - np.log(s.nz[:, None] + s.n_words * cfg.beta + np.arange(self.size[i])).sum(axis=1)
            w, k = self.words[i], self.counts[i]
            for step in range(int(k.max(initial=0))):
                out = out + np.log(s.tw[:, w[k > step]] + cfg.beta + step).sum(axis=1)
        if self.profile and i in s.ends:
            e = s.ends[i]
            out = out + log_factor(self._link_scores(i, e), e.aug).sum(axis=1)
        if i in s.terms:
            out = out + s.terms[i][0]
        return out

    def topics_of(self, i: int, e: Ends) -> np.ndarray:
        """The topics that the links carry: those of their sources."""
        return np.where(e.source, self.z[i], np.where(e.doc >= 0, self.z[e.doc], e.topic))

    def _weighted(self, e: Ends, z: np.ndarray | None = None) -> np.ndarray:
        """([topics,] ends, communities): the community factor of each end were its own user wholly in a community, at all topics or at one of each end."""
        p = self.s.pi[e.other]
        if z is not None:
            g = self.s.tensor[z]
            return np.where(e.source[:, None], (g @ p[:, :, None])[:, :, 0], (g.transpose(0, 2, 1) @ p[:, :, None])[:, :, 0])
        g = self.s.tensor
        got = np.empty((len(g), len(p), g.shape[1]))
        for side, h in ((e.source, g), (~e.source, g.transpose(0, 2, 1))):
            if side.any():
                got[:, side] = (h @ p[side].T).transpose(0, 2, 1)
        return got

    def _link_scores(self, i: int, e: Ends, z: np.ndarray | None = None) -> np.ndarray:
        """([topics,] ends): the sum of the factors in use."""
        x = np.zeros((len(self.s.tensor), len(e.other)) if z is None else len(e.other))
        if "community" in self.cfg.factors:
            x = x + self._weighted(e, z) @ self.s.pi[self.user[i]]
        if "topic" in self.cfg.factors:
            x = x + (self.s.pop[:, e.tbin] if z is None else self.s.pop[z, e.tbin])
        if "individual" in self.cfg.factors:
            x = x + e.own
        return x

    def community_scores(self, i: int) -> np.ndarray:
        """Log weights of the communities of document i, which is out of ``uc`` and ``ct``; ``pi`` still has it."""
        cfg, s, u, z = self.cfg, self.s, self.user[i], self.z[i]
        mine, total = s.uc[u], s.uc[u].sum() + 1
        out = np.log(mine + cfg.community_prior)
        if cfg.use_text:
            out = out + np.log(s.ct[:, z] + cfg.topic_prior) - np.log(s.ct.sum(axis=1) + cfg.topics * cfg.topic_prior)
        if cfg.use_friends and u in s.friends:
            v, lam = s.friends[u]
            near = s.pi[v]
            x = (near @ mine / total)[:, None] + near / total
            out = out + log_factor(x, lam[:, None]).sum(axis=0)
        if cfg.use_friends and u in s.moments:
            s1, q = s.moments[u]
            out = out + s1 / (2 * total) - (q @ mine / total**2 + np.diag(q) / (2 * total**2))
        if self.profile and "community" in cfg.factors and i in s.ends:
            e = s.ends[i]
            topics = self.topics_of(i, e)
            g = self._weighted(e, topics)
            x = self._link_scores(i, e, topics)[:, None] + (g - g[:, self.c[i], None]) / total
            out = out + log_factor(x, e.aug[:, None]).sum(axis=0)
        if i in s.terms:
            out = out + s.terms[i][1]
        return out

    def sweep(self, rng: np.random.Generator) -> None:
        """Draws topic, then community, of each document in turn."""
        cfg, s = self.cfg, self.s
        pick = (lambda x: int(np.argmax(x))) if cfg.draw == "argmax" else (lambda x: int(np.argmax(x - np.log(-np.log(rng.random(len(x)))))))
        for i in range(len(self.user)):
            u, w, k, n = self.user[i], self.words[i], self.counts[i], self.size[i]
            s.ct[self.c[i], self.z[i]] -= 1
            if cfg.use_topics:
                s.tw[self.z[i], w] -= k
                s.nz[self.z[i]] -= n
                self.z[i] = pick(self.topic_scores(i))
                s.tw[self.z[i], w] += k
                s.nz[self.z[i]] += n
            if not cfg.freeze_communities:
                s.uc[u, self.c[i]] -= 1
                self.c[i] = pick(self.community_scores(i))
                s.uc[u, self.c[i]] += 1
                s.pi[u] = s.uc[u] / s.uc[u].sum()
            s.ct[self.c[i], self.z[i]] += 1


@dataclass
class SmallGraph:
    """A graph in arrays: users 0.., documents with user, bin and words, links by position of document."""

    n_users: int
    user: np.ndarray
    tbin: np.ndarray
    words: list[np.ndarray]
    counts: list[np.ndarray]
    friends: np.ndarray
    diffs: np.ndarray
    n_words: int

    @property
    def bins(self) -> int:
        return int(self.tbin.max(initial=0)) + 1


def features_of(g: SmallGraph) -> np.ndarray:
    """(users, 2): followers over followees, diffusing documents over documents; zero where the denominator is."""
    share = lambda a, b: np.divide(a, b, out=np.zeros(len(a)), where=b > 0)
    count = lambda x: np.bincount(x, minlength=g.n_users).astype(float)
    return np.stack([share(count(g.friends[:, 1]), count(g.friends[:, 0])), share(count(g.user[np.unique(g.diffs[:, 0])]), count(g.user))], axis=1)


class SerialSampler:
    """The whole algorithm on one machine: documents in turn, both kinds of augmentation variables, diffusion profile and weights."""

    def __init__(self, g: SmallGraph, cfg: ProfilerConfig, start: np.ndarray | None = None) -> None:
        self.g, self.cfg = g, cfg
        rng = self.rng = np.random.default_rng(cfg.seed)
        n, C, Z = len(g.user), cfg.communities, cfg.topics  # noqa: N806
        c, z = rng.integers(0, C, n), rng.integers(0, Z, n)
        if start is not None:
            c = start.copy()
        tw, ct, uc = np.zeros((Z, g.n_words)), np.zeros((C, Z)), np.zeros((g.n_users, C))
        for i in range(n):
            tw[z[i], g.words[i]] += g.counts[i]
        np.add.at(ct, (c, z), 1)
        np.add.at(uc, (g.user, c), 1)
        self.nu = np.zeros(4)
        feats = features_of(g)
        self.design = lambda u, v: np.concatenate([feats[u], feats[v]], axis=1)
        state = State(tw, tw.sum(axis=1), ct, uc, uc / np.maximum(1, uc.sum(axis=1, keepdims=True)), np.zeros((Z, C, C)), np.zeros((Z, g.bins)), g.n_words)
        self.kernel = Kernel(cfg, state, g.user, c, z, g.words, g.counts)
        pairs = [g.friends]
        if cfg.use_diffusion and cfg.diffusion_kind == "similarity":
            pairs.append(np.stack([g.user[g.diffs[:, 0]], g.user[g.diffs[:, 1]]], axis=1))
        self.links = np.concatenate(pairs)
        self.negative = self._negatives()
        self.sums = [0.0, 0.0, 0.0]
        self.kept = 0
        self.trace: list[float] = []

    def _negatives(self) -> np.ndarray:
        """As many document pairs as diffusion links, none of them a link; redrawn until they are."""
        g, have = self.g, {tuple(x) for x in self.g.diffs.tolist()}
        out: set[tuple[int, int]] = set()
        rows = []
        for i in g.diffs[:, 0].tolist():
            for _ in range(50):
                j = int(self.rng.integers(len(g.user)))
                if g.user[i] != g.user[j] and (i, j) not in have and (i, j) not in out:
                    out.add((i, j))
                    rows.append((i, j))
                    break
        return np.array(rows, dtype=int).reshape(-1, 2)

    def refresh(self) -> None:
        """The diffusion profile, popularity and tensor of the assignment in force."""
        s, k, g, cfg = self.kernel.s, self.kernel, self.g, self.cfg
        eta = np.zeros((cfg.communities, cfg.communities, cfg.topics))
        a, b = g.diffs[:, 0], g.diffs[:, 1]
        np.add.at(eta, (k.c[a], k.c[b], k.z[a]), 1.0)
        over = {"per_community": (1, 2), "joint": (0, 1, 2), "per_pair_topic": (2,)}[cfg.eta_norm]
        self.eta = eta / np.maximum(1e-12, eta.sum(axis=over, keepdims=True))
        theta = s.ct / np.maximum(1, s.ct.sum(axis=1, keepdims=True))
        s.tensor = np.einsum("cdz,cz,dz->zcd", self.eta, theta, theta)
        count = np.zeros((cfg.topics, g.bins))
        np.add.at(count, (k.z, g.tbin), 1.0)
        s.pop = {"raw": lambda: count, "log1p": lambda: np.log1p(count), "share": lambda: count / np.maximum(1, count.sum(axis=0))}[cfg.popularity]()

    def link_parts(self, pairs: np.ndarray) -> np.ndarray:
        """The scores of document pairs without the individual factor."""
        s, k, g, f = self.kernel.s, self.kernel, self.g, self.cfg.factors
        i, j = pairs[:, 0], pairs[:, 1]
        z = k.z[i] if self.cfg.link_topic == "source" else k.z[j]
        x = np.zeros(len(pairs))
        if "community" in f:
            x += np.einsum("ec,ecd,ed->e", s.pi[g.user[i]], s.tensor[z], s.pi[g.user[j]])
        if "topic" in f:
            x += s.pop[z, g.tbin[i]]
        return x

    def scores(self, pairs: np.ndarray) -> np.ndarray:
        own = self.design(self.g.user[pairs[:, 0]], self.g.user[pairs[:, 1]]) @ self.nu if "individual" in self.cfg.factors else 0.0
        return self.link_parts(pairs) + own

    def augment(self, x: np.ndarray, salt: int) -> np.ndarray:
        if self.cfg.pg == "mean":
            return pg_mean_of(x)
        rng = KeyedRandom(np.arange(len(x)), self.cfg.seed * 7919 + salt)
        return pg_exact(x, rng) if self.cfg.pg == "exact" else pg_series(x, rng)

    def attach(self, number: int) -> None:
        """Draws the augmentation variables of all links and hands links to users and documents."""
        s, g, cfg = self.kernel.s, self.g, self.cfg
        s.friends, s.ends = {}, {}
        if cfg.use_friends and len(self.links):
            u, v = self.links[:, 0], self.links[:, 1]
            lam = self.augment(np.einsum("ec,ec->e", s.pi[u], s.pi[v]), 2 * number)
            a, b, aug = np.concatenate([u, v]), np.concatenate([v, u]), np.concatenate([lam, lam])
            order = np.argsort(a, kind="stable")
            for part in np.split(order, np.flatnonzero(np.diff(a[order])) + 1):
                s.friends[int(a[part[0]])] = (b[part], aug[part])
        if self.kernel.profile and len(g.diffs):
            delta = self.augment(self.scores(g.diffs), 2 * number + 1)
            own = self.design(g.user[g.diffs[:, 0]], g.user[g.diffs[:, 1]]) @ self.nu
            doc, other = g.diffs.T.ravel(), g.user[g.diffs[:, ::-1].T.ravel()]
            source = np.repeat([True, False], len(g.diffs))
            tbin, twice = np.tile(g.tbin[g.diffs[:, 0]], 2), np.arange(2 * len(g.diffs)) % len(g.diffs)
            order = np.argsort(doc, kind="stable")
            for part in np.split(order, np.flatnonzero(np.diff(doc[order])) + 1):
                at = g.diffs[twice[part], 0]
                s.ends[int(doc[part[0]])] = Ends(other[part], source[part], tbin[part], own[twice[part]], delta[twice[part]], self.kernel.z[at], at)

    def fit_nu(self) -> None:
        """Weights of the individual factor by gradient steps on links and as many pairs that are none."""
        both = np.concatenate([self.g.diffs, self.negative])
        y = np.repeat([1.0, 0.0], [len(self.g.diffs), len(self.negative)])
        x, rest = self.design(self.g.user[both[:, 0]], self.g.user[both[:, 1]]), self.link_parts(both)
        for _ in range(self.cfg.nu_steps):
            self.nu = self.nu + self.cfg.nu_rate * x.T @ (y - 1 / (1 + np.exp(-rest - x @ self.nu))) / max(1, len(y))

    def fit(self, sweeps: int | None = None) -> SerialSampler:
        sweeps = self.cfg.sweeps if sweeps is None else sweeps
        for number in range(sweeps):
            self.refresh()
            self.attach(number)
            self.kernel.sweep(self.rng)
            if self.kernel.profile and "individual" in self.cfg.factors and len(self.g.diffs):
                self.refresh()
                self.fit_nu()
            self.trace.append(self.log_joint())
            if number >= self.cfg.burnin:
                s = self.kernel.s
                self.sums = [a + b for a, b in zip(self.sums, (s.uc, s.ct, s.tw), strict=True)]
                self.kept += 1
        self.refresh()
        return self

    def log_joint(self) -> float:
        from commlens.functions.udfs import _lgamma

        s, cfg = self.kernel.s, self.cfg

        def part(n: np.ndarray, prior: float) -> float:
            rows = n.sum(axis=1)
            return float((_lgamma(n[n > 0] + prior) - _lgamma(np.array([prior]))).sum() - (_lgamma(rows + prior * n.shape[1]) - _lgamma(np.array([prior * n.shape[1]]))).sum())

        sure = lambda x: -float(np.logaddexp(0, -x).sum())
        total = part(s.uc, cfg.community_prior) + part(s.ct, cfg.topic_prior) + part(s.tw, cfg.beta)
        total += sure(np.einsum("ec,ec->e", s.pi[self.links[:, 0]], s.pi[self.links[:, 1]])) if cfg.use_friends and len(self.links) else 0.0
        return total + (sure(self.scores(self.g.diffs)) if self.kernel.profile and len(self.g.diffs) else 0.0)

    def estimates(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Memberships, content profiles and topics from the counts averaged over the sweeps after ``burnin``, or the last ones."""
        s, cfg = self.kernel.s, self.cfg
        counts = [x / self.kept for x in self.sums] if self.kept else [s.uc, s.ct, s.tw]
        smooth = lambda n, prior: (n + prior) / (n.sum(axis=1, keepdims=True) + prior * n.shape[1])
        return smooth(counts[0], cfg.community_prior), smooth(counts[1], cfg.topic_prior), smooth(counts[2], cfg.beta)
