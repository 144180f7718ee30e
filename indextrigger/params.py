"""Switches of every stage, one frozen class per stage, and two presets."""

from __future__ import annotations

from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class BurstParams:
    tail: str = "strict"  # strict: P(X<n); inclusive: P(X<=n); pmf: P(X=n)
    expected: str = "pooled"  # pooled, mean_rate, quiet
    threshold: float = 0.95
    require_presence: bool = False
    sparsify: bool = True
    quiet_rounds: int = 3


@dataclass(frozen=True)
class VolatilityParams:
    horizon: int = 4
    mode: str = "trailing"  # trailing, centered, within (an index of finer steps inside each window)
    fit: str = "moments"  # moments, mle
    levels: int | None = 10


@dataclass(frozen=True)
class TopicParams:
    influence: str = "sum"  # sum, candidate, mean, off
    seed: str = "influence"  # influence, pair
    singleton: str = "self"  # self, drop, zero
    min_link: float = 0.0  # a candidate needs an affinity above this with a member
    min_pair_objective: float = 0.0
    max_topic_size: int | None = None
    factors: str = "all"  # all, no_documents, no_time: what the objective leaves out
    burst_threshold: float = 0.7


@dataclass(frozen=True)
class GroupParams:
    method: str = "kmeans"  # kmeans, threshold
    k: int | None = None
    max_k: int | None = None
    merge_all_at: float = 0.6
    cosine: float = 0.5


@dataclass(frozen=True)
class ChainParams:
    link_threshold: float = 0.1
    require_gain: bool = True
    branching: str = "composite"  # composite, fork
    beam: int | None = None  # chains of a step beyond which no further fork is taken
    weight: str = "objective"  # objective, none
    merge_at: float = 0.5
    linkage: str = "average"  # single, average, complete


@dataclass(frozen=True)
class Params:
    burst: BurstParams = field(default_factory=BurstParams)
    volatility: VolatilityParams = field(default_factory=VolatilityParams)
    topic: TopicParams = field(default_factory=TopicParams)
    group: GroupParams = field(default_factory=GroupParams)
    chain: ChainParams = field(default_factory=ChainParams)
    #: Rows that one grouped map may hold; they follow features and windows, not documents. More is refused.
    max_local_rows: int = 2_000_000

    def but(self, **changes) -> "Params":
        return replace(self, **changes)


#: Strict tail, series zeroed outside bursts.
FLAGSHIP = Params()
#: The same with short topics, few groups a window and few forks a step, for quick looks.
CAPPED = Params(topic=TopicParams(max_topic_size=8), group=GroupParams(max_k=12), chain=ChainParams(beam=64))
#: Inclusive tail on words that are present and raw series, the forms that the prose describes.
FAITHFUL = Params(burst=BurstParams(tail="inclusive", require_presence=True, sparsify=False), volatility=VolatilityParams(levels=10))
