"""Parameters of a mining run."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class MinerConfig:
    """theta: least support, a count, or a share of all vertices if ``relative``. max_len: longest path.

    max_reach: most hops of a reach pattern (None: max_len; 0: no limit). psi: damping of the tail bound (None:
    exact). rho: share of source vertices in every stratum (None: all). policy: ``pruned`` or ``prefix_only``. bound:
    ``global`` (largest in-degree of the graph) or ``per_label``. rule_form: ``single_pass``, ``merged``, ``lattice``, ``bitmap`` or ``auto``
    (``merged`` or ``lattice``, by the rows that they need; the plain policy always takes ``single_pass``). estimator: supports of sampled runs by the ``ratio`` rho, or by each stratum's own ``stratum_weight``. allow_empty: whether a
    position may ask for no item. placement: how sources are dealt out to ``parallelism`` partitions (``greedy``, ``hash``, ``snake``; None: by
    Spark). parallelism: most partitions of any step (None: as the session has it). deadline_s: seconds after which a run stops with what it has.
    """

    theta: float
    relative: bool = False
    max_len: int = 2
    max_reach: int | None = None
    reach: bool = True
    max_items: int | None = None
    psi: float | None = None
    rho: float | None = None
    sample_mode: str = "quota"
    seed: int = 42
    policy: str = "pruned"
    bound: str = "global"
    rule_form: str = "auto"
    estimator: str = "ratio"
    min_len: int = 1
    keep_dominated: bool = False
    allow_empty: bool = False
    drop_implied: bool = False
    placement: str | None = None
    parallelism: int | None = None
    deadline_s: float | None = None

    def __post_init__(self):
        if self.theta <= 0 or self.max_len < 0:
            raise ValueError("theta must be positive and max_len not negative")
        for name in ("psi", "rho"):
            x = getattr(self, name)
            if x is not None and not 0 <= x <= 1 or name == "rho" and x == 0:
                raise ValueError(f"{name} must lie between 0 and 1")
        for name, known in (("policy", ("pruned", "prefix_only")), ("bound", ("global", "per_label")), ("rule_form", ("auto", "single_pass", "merged", "lattice", "bitmap")), ("estimator", ("ratio", "stratum_weight")), ("placement", (None, "greedy", "hash", "snake")), ("sample_mode", ("quota", "threshold"))):
            if getattr(self, name) not in known:
                raise ValueError(f"{name} must be one of {known}")

    @property
    def hops(self) -> int:
        return self.max_len if self.max_reach is None else self.max_reach

    def but(self, **changes) -> MinerConfig:
        return replace(self, **changes)
