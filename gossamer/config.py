"""The settings of one run."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class StopRule:
    """Ends a run early: samples touched, seconds, or an error level reached."""

    max_touched: int | None = None
    max_seconds: float | None = None
    target_error: float | None = None


@dataclass(frozen=True)
class DescentConfig:
    """Parameters of all methods. ``eps``: step size; ``b``: mini-batch; ``steps``: rounds a worker; ``workers``: n."""

    loss: str = "prototypes"  # prototypes | squares | logistic: the last two read the target from the end of each sample
    k: int = 3
    eps: float = 0.75
    b: int = 8
    steps: int = 8
    workers: int = 4
    seed: int = 7
    partition: str = "exact"  # exact | hash: sizes equal up to chance | scan: samples stay with the task that reads them
    remainder: str = "drop"  # of m mod n samples: drop | spread
    draw: str = "shuffle"  # shuffle | replace
    draw_from: str = "local"  # with replacement: from the worker's own samples (local) or from all (global)
    init: str = "first"  # first | sample | bounds | zeros
    comm: str = "gossip"  # gossip | silent | sync
    fanout: int = 1
    scope: str = "any"  # recipients: any | other_node
    threads: int = 1  # workers a node
    block_frac: float = 1.0
    buffers: int = 1
    max_age: int = 1
    delay: str = "uniform"  # ages up to max_age: uniform | geometric
    empty_rule: str = "null"  # null | zero_norm: a received state of zeros counts as an empty buffer
    race: str = "overwrite"  # overwrite | torn | none
    consume: bool = True  # a buffer is emptied when read; if not, a state stays until another takes its place
    window: bool = True
    window_scope: str = "message"  # message | block | state: whole states only
    blend_gain: str = "eps"  # eps | unit
    reduce: str = "mean"  # mean | sum
    normalise: str = "batch"  # batch | cluster
    final: str = "first"  # first | average
    comm_every: int = 1
    stretch: int = 1
    stop: StopRule = StopRule()

    def with_(self, **changes) -> DescentConfig:
        return replace(self, **changes)

    def validate(self, m: int | None = None) -> DescentConfig:
        parallel = self.comm != "silent"
        problems = [
            (self.eps <= 0, "eps must be positive"), (self.k < 1 or self.b < 1 or self.steps < 1 or self.workers < 1, "k, b, steps and workers start at 1"),
            (parallel and self.workers < 2, "messages need at least two workers"), (parallel and not 1 <= self.fanout <= max(1, self.workers - 1), "fanout is at most workers - 1"),
            (not 0 < self.block_frac <= 1, "block_frac is in (0, 1]"), (self.buffers < 1 or self.max_age < 1 or self.comm_every < 1 or self.stretch < 1, "buffers, max_age, comm_every and stretch start at 1"),
            (self.race not in ("overwrite", "torn", "none"), "race is overwrite, torn or none"), (self.window_scope not in ("message", "block", "state"), "window_scope is message, block or state"),
            (self.partition not in ("exact", "hash", "scan") or self.draw_from not in ("local", "global"), "partition is exact, hash or scan; draw_from is local or global"),
            (self.draw_from == "global" and self.draw != "replace", "draws from all samples are with replacement"), (self.partition != "exact" and self.draw != "shuffle", "draws with replacement need the exact partition"),
            (not self.consume and (self.race == "none" or self.comm == "sync"), "states stay in buffers that others overwrite"),
            (self.loss not in ("prototypes", "squares", "logistic"), "loss is prototypes, squares or logistic"), (self.loss != "prototypes" and self.k != 1, "a loss with a target has one block: k = 1"),
            (self.scope not in ("any", "other_node") or self.threads < 1, "scope is any or other_node"), (self.delay not in ("uniform", "geometric"), "delay is uniform or geometric"), (self.empty_rule not in ("null", "zero_norm"), "empty_rule is null or zero_norm"),
            (parallel and self.scope == "other_node" and (self.workers % self.threads > 0 or self.fanout > self.workers - self.threads), "nodes are full and have enough other workers"),
        ]
        if m is not None:
            problems += [(self.k > m, "k is at most the number of samples"), (m // self.workers < 1, "every worker needs a sample")]
        for wrong, why in problems:
            if wrong:
                raise ValueError(why)
        return self

    def within(self, m: int | None = None) -> DescentConfig:
        """The same with as many rounds as the stop rule's samples allow."""
        if self.stop.max_touched is None:
            return self
        return self.with_(steps=max(1, min(self.steps, -(-self.stop.max_touched // (self.b * self.workers)))))

    @property
    def pull(self) -> float:
        """Largest weight of the pull towards peers; above 1 a run may diverge."""
        n = self.buffers if self.race != "none" else max(self.buffers, self.fanout)
        return (self.eps if self.blend_gain == "eps" else 1.0) * n / (n + 1)


def scale_eps(eps: float, b: int, rule: str = "none") -> float:
    """Step size for a mini-batch of ``b``, from one that suits single samples."""
    return {"none": eps, "linear": eps * b, "sqrt": eps * b**0.5}[rule]
