"""Settings of similarity, index, links and search. Frozen, so that they can be stored with an index."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass


class Stored:
    def to_json(self) -> str:
        return json.dumps(asdict(self))


@dataclass(frozen=True)
class SimConfig(Stored):
    metric: object = "ip"  # a registered name (ip, cosine, l2 negated, or one's own) or a function of two matrices
    gamma: int = 1
    short: str = "literal"  # divide by gamma, or by the tokens 'found'
    mode: str = "exact"  # or clustered
    beta: int | None = None
    rounds: int = 5

    def __post_init__(self):
        from .functions.kernel import metric_of

        metric_of(self.metric)
        if self.gamma < 1 or self.short not in ("literal", "found") or self.mode not in ("exact", "clustered"):
            raise ValueError("gamma >= 1, short literal/found, mode exact/clustered")
        if self.mode == "clustered" and self.metric != "ip":
            raise ValueError("shortlists by centres need the inner product")


@dataclass(frozen=True)
class IndexConfig(Stored):
    M: int = 32
    ef_construction: int = 128
    m_l: float | None = None
    gamma: int = 1
    edge_fn: str = "fused"  # fused, raw, one_sided, sum
    edge_sim: str = "exact"  # or clustered
    beta: int | None = None
    trim: str = "one_sided"  # or mirror
    descend: str = "all"  # or best
    select: str = "nearest"  # or diverse
    seed: int = 42
    n_shards: int = 1
    shard_by: str = "hash"  # or centroid

    def __post_init__(self):
        known = {"edge_fn": ("fused", "raw", "one_sided", "sum"), "edge_sim": ("exact", "clustered"), "trim": ("one_sided", "mirror"),
                 "descend": ("all", "best"), "select": ("nearest", "diverse"), "shard_by": ("hash", "centroid")}
        for name, values in known.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name} is one of {', '.join(values)}")
        if self.M < 1 or self.ef_construction < 1 or self.n_shards < 1 or self.gamma < 1:
            raise ValueError("M, ef_construction, n_shards and gamma are 1 or more")

    @property
    def level_scale(self) -> float:
        return self.m_l if self.m_l is not None else 1 / math.log(self.M)


@dataclass(frozen=True)
class LinkConfig(Stored):
    M: int = 32
    factor: int = 5  # nearest tokens looked at for every linked object
    gamma: int = 1
    how: str = "exact"  # all tokens of the shard; or cells, or a token graph
    ef: int = 64  # list of the token graph's searches, at least factor * M
    probes: int = 4  # cells looked at

    def __post_init__(self):
        if self.how not in ("exact", "cells", "graph") or min(self.M, self.factor, self.gamma, self.probes) < 1:
            raise ValueError("how is exact, cells or graph; M, factor, gamma and probes are 1 or more")


@dataclass(frozen=True)
class SearchConfig(Stored):
    k: int = 10
    ef: int | None = None
    gamma: int = 1
    linked: bool = True
    mode: str = "exact"  # score while walking: exact or clustered
    final: str = "exact"  # score of answers: exact again, or the same
    scale: float = 1.0  # squared length of token vectors: 1 for unit vectors
    beta: int | None = None
    distinct_pops: bool = True
    expand_layers: str = "base"  # or all
    probe_shards: int | None = None

    def __post_init__(self):
        if self.ef is not None and self.ef < self.k:
            raise ValueError("ef must be at least k")
        if self.mode not in ("exact", "clustered") or self.final not in ("exact", "same") or self.expand_layers not in ("base", "all") or self.scale <= 0:
            raise ValueError("mode exact/clustered, final exact/same, expand_layers base/all, scale above 0")

    @property
    def width(self) -> int:
        return self.ef or max(self.k, 128)
