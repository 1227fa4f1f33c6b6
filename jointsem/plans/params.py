"""Parameters of the joint method, with the defaults of its evaluation."""

from __future__ import annotations

from dataclasses import dataclass, replace


def default_batch_size(k: int) -> int:
    return max(200, 10 * k)


@dataclass(frozen=True)
class Params:
    """edge_mode: pairs, cluster_labels, pairwise, pairwise_context.  assign: matching, independent, with_examples, majority.
    score_assign: order, matching, independent.  proxy: rows, ladder (light, then strong where light is less sure than ladder_tau), batch or rubric.  rounds_seen: pair_mean (annotations per pair) or rounds.  start: random or warm."""

    batch: int | None = None
    sample: int = 80
    max_rounds: int = 800
    stop_share: float = 0.2
    edge_mode: str = "pairs"
    transitive: bool = True
    unseen_weight: float = 0.5
    pair_rounds: int = 1
    restarts: int = 2
    start: str = "warm"
    rounds_seen: str = "pair_mean"
    assign: str = "matching"
    weight: str = "logprob"
    n_examples: int = 3
    score_assign: str = "order"
    m_sort: int = 20
    cluster_tier: str = "strong"
    assign_tier: str = "strong"
    cluster_names: str = "identity"
    on_infeasible: str = "proxy_all"
    call_batch: int = 50
    proxy: str = "rows"
    ladder_tau: float = 0.7
    seed: str = "joint"

    def batch_size(self, k: int) -> int:
        return self.batch or default_batch_size(k)

    def but(self, **changes) -> Params:
        return replace(self, **changes)
