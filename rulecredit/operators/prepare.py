"""From raw columns to categorical tuples: sampling, binning, compression."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def sample_rows(df: DataFrame, n: int, seed: int = 0, key: list[str] | None = None) -> DataFrame:
    """The n rows with the smallest MD5 of seed and key (default: all columns): the same rows for any partitioning and engine."""
    cols = [F.col(c) for c in key or df.columns]
    return df.orderBy(F.md5(F.concat_ws("|", F.lit(str(seed)), *[c.cast("string") for c in cols])), *cols).limit(n)


@dataclass(frozen=True)
class Bins:
    """How one column becomes an attribute."""

    kind: str
    count: int = 0
    at: tuple = field(default=())

    @staticmethod
    def equal_width(n: int) -> Bins:
        return Bins("width", n)

    @staticmethod
    def equal_depth(n: int, exact: bool = False) -> Bins:
        return Bins("depth_exact" if exact else "depth", n)

    @staticmethod
    def cuts(*at: float) -> Bins:
        return Bins("cuts", at=tuple(at))

    @staticmethod
    def top_k(n: int) -> Bins:
        return Bins("top", n)

    @staticmethod
    def part(name: str) -> Bins:
        return Bins("part", at=(name,))

    @staticmethod
    def keep() -> Bins:
        return Bins("keep")


def _label(c: Column, cuts: list[float], labels: str) -> Column:
    """Half-open ranges ``lo-hi`` between the cuts, or their numbers from 0."""
    if labels == "index":
        return F.when(c.isNotNull(), sum(((c >= x).cast("int") for x in cuts), F.lit(0)).cast("string"))
    names = [f"<{cuts[0]:g}"] + [f"{a:g}-{b:g}" for a, b in zip(cuts, cuts[1:])] + [f">={cuts[-1]:g}"] if cuts else ["all"]
    out = F.lit(names[0])
    for cut, name in zip(cuts, names[1:]):
        out = F.when(c >= cut, name).otherwise(out)
    return F.when(c.isNotNull(), out)


def fit_bins(df: DataFrame, spec: dict[str, Bins]) -> dict[str, list]:
    """Cut points of all fitted columns in one aggregate; a few numbers a column reach the driver."""
    aggs, found = [], {}
    for c, b in spec.items():
        x = F.col(c).cast("double")
        if b.kind == "width":
            aggs += [F.min(x).alias(f"{c}__lo"), F.max(x).alias(f"{c}__hi")]
        elif b.kind.startswith("depth"):
            shares = F.array(*[F.lit(i / b.count) for i in range(1, b.count)])
            pick = F.percentile if b.kind == "depth_exact" else F.percentile_approx
            aggs.append(pick(x, shares).alias(f"{c}__q"))
    row = df.agg(*aggs).first() if aggs else None
    for c, b in spec.items():
        if b.kind == "width":
            lo, hi = row[f"{c}__lo"], row[f"{c}__hi"]
            found[c] = [] if lo is None or lo == hi else [lo + (hi - lo) * i / b.count for i in range(1, b.count)]
        elif b.kind.startswith("depth"):
            found[c] = sorted(set(row[f"{c}__q"] or []))
        elif b.kind == "cuts":
            found[c] = list(b.at)
        elif b.kind == "top":
            top = df.where(F.col(c).isNotNull()).groupBy(c).count().orderBy(F.desc("count"), c).limit(b.count)
            found[c] = [r[c] for r in top.collect()]
    return found


def discretize(df: DataFrame, spec: dict[str, Bins], nulls: str = "none", max_distinct: int = 1000, labels: str = "range") -> DataFrame:
    """One STRING column per entry of ``spec``; bins are named by their ``range`` or ``index``.

    ``nulls``: ``none`` (no element) or ``element`` (a value of its own). Kept columns
    with more than ``max_distinct`` values are refused: bin them first.
    """
    kept = [c for c, b in spec.items() if b.kind == "keep"]
    if kept:
        sizes = df.agg(*[F.approx_count_distinct(c).alias(c) for c in kept]).first().asDict()
        wide = {c: n for c, n in sizes.items() if n > max_distinct}
        if wide:
            raise ValueError(f"columns need bins: {wide}")
    cuts = fit_bins(df, spec)
    out = []
    for c, b in spec.items():
        if b.kind in ("width", "depth", "depth_exact", "cuts"):
            e = _label(F.col(c), cuts[c], labels)
        elif b.kind == "top":
            e = F.when(F.col(c).isin(cuts[c]), F.col(c).cast("string")).when(F.col(c).isNotNull(), "other")
        elif b.kind == "part":
            e = F.extract(F.lit(b.at[0]), F.col(c)).cast("string")
        else:
            e = F.col(c).cast("string")
        out.append((F.coalesce(e, F.lit("∅")) if nulls == "element" else e).alias(c))
    return df.select(*out)


def compress(view: DataFrame, weight: str | None = None) -> DataFrame:
    """Distinct tuples with their number ``c`` (or summed weight): one shuffle with map-side combine."""
    attrs = [c for c in view.columns if c != weight]
    return view.groupBy(*attrs).agg((F.sum(weight) if weight else F.count("*")).alias("c"))
