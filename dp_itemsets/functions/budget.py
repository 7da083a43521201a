"""Privacy budgets: what each step spends, never more than there is."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

REPORT_SCHEMA = "step string, label string, eps_spent double, sensitivity double, mechanism string, output_size int, warning string"

#: Shares of the budget for the rank, the items and pairs, and the bins.
ALPHAS = (0.1, 0.4, 0.5)


@dataclass
class BudgetLedger:
    eps: float
    entries: list[tuple] = field(default_factory=list)

    @property
    def spent(self) -> float:
        return sum(e[2] for e in self.entries)

    def spend(self, step: str, eps: float, label: str = "", sensitivity: float = 1.0, mechanism: str = "", output_size: int = 0, warning: str = "") -> float:
        """Books a step under sequential composition and returns its budget."""
        if eps < 0 or self.spent + eps > self.eps * (1 + 1e-9):
            raise ValueError(f"{step}: {self.spent} + {eps} is more than the budget {self.eps}")
        self.entries.append((step, label, float(eps), float(sensitivity), mechanism, int(output_size), warning))
        return eps

    def report(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.entries, REPORT_SCHEMA)


def split_budget(eps: float, lam: int, pairs: int, alphas: tuple[float, float, float] = ALPHAS, single_limit: int = 12) -> dict[str, float]:
    """Budgets of the rank, the items, the pairs and the bins.  One basis needs no pairs."""
    if min(alphas) < 0 or abs(sum(alphas) - 1) > 1e-9:
        raise ValueError("the shares must add up to 1")
    first, second, third = (a * eps for a in alphas)
    pairs = 0 if lam <= single_limit else max(pairs, 0)
    items = second * lam / (lam + pairs) if lam + pairs else second
    return {"rank": first, "items": items, "pairs": second - items if pairs else 0.0, "bins": third}


def pairs_to_request(k: int, eta: float, lam: int, rule: str = "root") -> int:
    """How many pairs to draw for a top-k with ``lam`` items.

    ``naive`` asks for what is left of eta * k; ``root`` divides that by the
    root of its ratio to lam where it exceeds lam.  Never below 0 or above the
    number of pairs that lam items have.
    """
    left = eta * k - lam
    if left <= 0:
        return 0
    if rule == "root":
        left /= max(1.0, left / max(lam, 1)) ** 0.5
    elif rule != "naive":
        raise ValueError("the rule is root or naive")
    return min(int(left + 1e-9), lam * (lam - 1) // 2)
