"""Cost model and plan choice, calibrated on published token totals (two workloads only: treat as defaults)."""

from __future__ import annotations

from dataclasses import dataclass

from mediarel.functions.semantic import FOOTAGE_TOKENS, NARRATION_TOKENS, USD_PER_MILLION


@dataclass(frozen=True)
class Estimate:
    """A plan with its expected tokens and recall; ``recall`` None means unmeasured."""

    plan: str
    tokens: float
    recall: float | None = None

    @property
    def usd(self) -> float:
        return self.tokens * USD_PER_MILLION / 1_000_000


def tokens(plan: str, duration_s: float, selectivity: float = 1.0) -> float:
    """Tokens of a plan over footage of a duration: narrow pays the narration and its share of the footage."""
    footage, narration = FOOTAGE_TOKENS / 1000 * duration_s, NARRATION_TOKENS / 1000 * duration_s
    return {"direct": footage, "narration": narration, "narrow": narration + selectivity * footage}[plan]


def break_even_selectivity() -> float:
    """Below this selectivity the narrow plan takes fewer tokens than the direct one."""
    return 1 - NARRATION_TOKENS / FOOTAGE_TOKENS


def choose(estimates: list[Estimate], min_recall: float = 0.0, budget_usd: float | None = None) -> Estimate:
    """Cheapest plan that reaches the recall and the budget; ties go to the higher recall."""
    fits = [e for e in estimates if (e.recall is not None and e.recall >= min_recall or min_recall <= 0) and (budget_usd is None or e.usd <= budget_usd)]
    if not fits:
        raise ValueError("no plan reaches the recall within the budget")
    return min(fits, key=lambda e: (e.tokens, -(e.recall or 0), e.plan))
