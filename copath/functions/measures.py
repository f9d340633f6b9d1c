"""Rule measures as expressions over four counts: both sides, antecedent, consequent, all vertices."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from copath.plans.store import cut

MEASURES: dict[str, Callable[[Column, Column, Column, Column], Column]] = {}


def register_measure(name: str, f: Callable[[Column, Column, Column, Column], Column]) -> None:
    MEASURES[name] = f


register_measure("rel_support", lambda xy, x, y, n: xy / n)
register_measure("confidence", lambda xy, x, y, n: xy / x)
register_measure("lift", lambda xy, x, y, n: xy * n / (x * y))
register_measure("jaccard", lambda xy, x, y, n: xy / (x + y - xy))
register_measure("leverage", lambda xy, x, y, n: xy / n - (x / n) * (y / n))
register_measure("conviction", lambda xy, x, y, n: F.when(xy < x, (1 - y / n) / (1 - xy / x)))
register_measure("cosine", lambda xy, x, y, n: xy / F.sqrt(x * y))
register_measure("kulczynski", lambda xy, x, y, n: (xy / x + xy / y) / 2)

BASIC = ("rel_support", "confidence", "lift", "jaccard")


def score(rules: DataFrame, names: tuple[str, ...] = BASIC) -> DataFrame:
    """Adds measures to rows of abs_support, support_x, support_y, n_vertices."""
    counts = [F.col(c).cast("double") for c in ("abs_support", "support_x", "support_y", "n_vertices")]
    return rules.withColumns({m: MEASURES[m](*counts) for m in names})


def filter_rules(rules: DataFrame, min_conf: float | None = None, min_lift: float | None = None, min_jaccard: float | None = None) -> DataFrame:
    for name, least in (("confidence", min_conf), ("lift", min_lift), ("jaccard", min_jaccard)):
        if least is not None:
            rules = rules.where(F.col(name) >= least)
    return rules


def best_consequents(antecedents: DataFrame, rules: DataFrame, k: int = 3, by: str = "confidence") -> DataFrame:
    """x, y, measures of the best k rules of each antecedent (a column x); ties by text. A lateral join with a limited subquery."""
    rest = ", ".join(f"q.`{c}`" for c in rules.columns if c != "x")
    best = f"SELECT {rest} FROM {{rules}} AS q WHERE q.x = a.x ORDER BY q.`{by}` DESC, q.y LIMIT {int(k)}"
    # A table of its own: both sides may come from the same run, and the subquery must not share their attributes.
    return rules.sparkSession.sql(f"SELECT a.x, b.* FROM {{antecedents}} AS a, LATERAL ({best}) AS b", antecedents=antecedents.select("x").distinct(), rules=cut(rules))


def top_rules(rules: DataFrame, by: str = "lift", k: int = 10, per: str | None = None) -> DataFrame:
    """The best k rules by a measure, overall or for each value of ``per``; ties by text."""
    from pyspark.sql import Window

    order = [F.desc(by), F.col("x"), F.col("y")]
    if per is None:
        return rules.orderBy(*order).limit(k)
    return rules.withColumn("rank", F.row_number().over(Window.partitionBy(per).orderBy(*order))).where(F.col("rank") <= k)
