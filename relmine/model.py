"""Rules, settings and what a verdict holds."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from hashlib import md5


@dataclass(frozen=True)
class Relation:
    """A rule ``f(inputs) = output``.

    ``expr`` is an expression tree for arithmetic and string rules: a column
    name, ("lit", text) or (operator, operand, ...). A value dependency has none.
    """

    kind: str
    inputs: tuple[str, ...]
    output: str
    expr: tuple | str | None = None

    def __post_init__(self):
        if self.kind not in ("AR", "ST", "FD"):
            raise ValueError(f"unknown kind {self.kind}")
        if self.output in self.inputs:
            raise ValueError("a rule's output cannot be among its inputs")
        if not self.inputs or len(set(self.inputs)) < len(self.inputs):
            raise ValueError("inputs must be different columns, at least one")
        if (self.expr is None) != (self.kind == "FD"):
            raise ValueError("value dependencies alone have no expression")

    @property
    def columns(self) -> tuple[str, ...]:
        """Participating columns, inputs first."""
        return (*self.inputs, self.output)

    @property
    def arity(self) -> int:
        return len(self.inputs)

    @property
    def text(self) -> str:
        from relmine.functions.expressions import render

        return f"{', '.join(self.inputs)} -> {self.output}" if self.kind == "FD" else f"{render(self.expr)} = {self.output}"

    @property
    def cand_id(self) -> str:
        return md5(f"{self.kind}|{self.text}".encode()).hexdigest()[:12]

    def isomerous(self, other: Relation) -> bool:
        """Whether both rules join the same columns."""
        return set(self.columns) == set(other.columns)


@dataclass(frozen=True)
class Config:
    """Settings of a run; the thresholds are the published ones, the sampling sizes our own."""

    setting: str = "clean"
    tau: float | None = None
    alpha: float = 0.05
    eta: float = 0.5
    max_level: int = 4
    n_max: int = 10_000
    beta: int = 100
    z: float = 1.96
    seed: int = 42
    use_minimality: bool = True
    use_independence: bool = True
    use_bound: bool = True
    use_core: bool = True
    use_wilson: bool = True
    tight: bool = False
    subset_space: str = "nonempty"
    fd_mode: str = "recheck"
    row_pool: str = "satisfied"
    dirty_mode: str = "independence"
    core_check: str = "guarded"
    bound_mode: str = "exact"
    bound_rows: int = 10_000_000
    mode: str = "one_shot"
    yates: bool = False
    multiplicity: str = "none"
    min_effect: float = 0.0
    min_expected: float = 0.0
    it_columns: int = 0
    looks: str = "single"
    null_policy: str = "exclude_all_null"
    atol: float = 0.0
    rtol: float = 1e-9
    batch_rules: int = 64
    exclude: tuple[str, ...] = field(default_factory=tuple)

    def __post_init__(self):
        choices = {"setting": ("clean", "dirty"), "subset_space": ("nonempty", "proper"), "fd_mode": ("recheck", "induced"), "row_pool": ("satisfied", "all"),
                   "dirty_mode": ("independence", "drop_violations"), "core_check": ("guarded", "paper"), "bound_mode": ("exact", "sample"), "mode": ("one_shot", "staged"),
                   "multiplicity": ("none", "bonferroni", "benjamini_hochberg"), "looks": ("single", "spread"), "null_policy": ("exclude_all_null", "violate", "match")}
        for name, allowed in choices.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")
        if self.tau is None:
            object.__setattr__(self, "tau", 1.0 if self.setting == "clean" else 0.8)

    def but(self, **changes) -> Config:
        return replace(self, **changes)


CANDIDATE = "cand_id string, kind string, inputs array<string>, output string, arity int, rule string, hits bigint, n_rows bigint"
VERDICT = CANDIDATE + ", mt_pass boolean, it_pass boolean, it_column string, it_chi2 double, it_p double, bound double, trials bigint, survived bigint, score double, stop_reason string, reliable boolean"
