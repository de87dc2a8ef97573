"""Options of an annotation run."""

from __future__ import annotations

from dataclasses import dataclass

MODES = ("valued", "symbolic")
NEGATIONS = ("filter", "reject", "monus")


@dataclass(frozen=True)
class Options:
    """What a run may vary.

    ``mode``: *valued* keeps real aggregates beside their formal sums (in
    ``<name>_agg``) and really filters on them; *symbolic* replaces aggregates by
    their formal sums and drops no row on a comparison with one.
    ``reagg_style``: *printed* leaves the scaling of a re-aggregation in the
    annotation, *evaluable* moves it into the value.
    ``negation``: what NOT IN / NOT EXISTS / EXCEPT do with the inner side.
    ``exists_strategy``: *auto* joins on equalities, takes *prefix* for one order
    comparison (builder), else goes through the distinct outer values; *domain* always
    does the latter; *prefix* lists the inner side once where the condition is one order
    comparison, and each distinct outer value takes its part.
    ``limit_policy``: *value* chooses rows on original values (with a caveat),
    *reject* refuses LIMIT.
    """

    mode: str = "valued"
    algebra: str = "text"
    reagg_style: str = "printed"
    negation: str = "filter"
    exists_strategy: str = "auto"
    rewrite_distinct: bool = True
    suffix: str = "_agg"
    value_scale: int = 4
    max_text_bytes: int = 64 << 20
    frame_prov: bool = False
    limit_policy: str = "value"

    def __post_init__(self):
        if self.mode not in MODES or self.negation not in NEGATIONS:
            raise ValueError(f"unknown mode or negation: {self.mode}, {self.negation}")
        if self.exists_strategy not in ("auto", "domain", "prefix") or self.reagg_style not in ("printed", "evaluable"):
            raise ValueError("unknown strategy or style")
        if self.limit_policy not in ("value", "reject"):
            raise ValueError(f"unknown limit policy: {self.limit_policy}")

    @property
    def symbolic(self) -> bool:
        return self.mode == "symbolic"
