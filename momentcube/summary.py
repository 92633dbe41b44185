"""The moment summary: count, extremes and unscaled power sums of x and of ln x, as flat primitive columns.

Flat columns keep accumulation and merging inside code-generated hash aggregation with map-side partials. NULL is skipped;
NaN and infinities are dropped. Logs are usable only if every value is positive (n_pos = n). The empty summary
has n = 0 and NULL extremes.

Log policies travel with the state: ``shift`` keeps logs of x + shift and says by how much; ``split_sign`` keeps logs of positive
values and of mirrored negative ones, with the counts and inner ends of both halves.
"""

from __future__ import annotations

import struct
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, functions as F

STATE = "struct<n:bigint,n_pos:bigint,xmin:double,xmax:double,s:array<double>,l:array<double>,shift:double,n_neg:bigint,pmin:double,nmax:double,m:array<double>>"
_LEAST, _MOST = ("xmin", "pmin"), ("xmax", "nmax")


@dataclass(frozen=True)
class SummarySpec:
    """order: sums kept; power/log: families kept; log_policy: ignore, split_sign or shift (by a constant all cells share)."""

    order: int = 10
    power: bool = True
    log: bool = True
    log_policy: str = "ignore"
    shift: float = 0.0

    @property
    def s(self) -> list[str]:
        return [f"s{i}" for i in range(1, self.order + 1)] if self.power else []

    @property
    def l(self) -> list[str]:  # noqa: E743
        return [f"l{i}" for i in range(1, self.order + 1)] if self.log else []

    @property
    def neg(self) -> list[str]:
        return [f"m{i}" for i in range(1, self.order + 1)] if self.log and self.log_policy == "split_sign" else []

    @property
    def split(self) -> list[str]:
        """Count of negative values, least positive and greatest negative value: what a split by sign needs beside its sums."""
        return ["n_neg", "pmin", "nmax"] if self.neg else []

    @property
    def sums(self) -> list[str]:
        return ["n", "n_pos", *self.split[:1], *self.s, *self.l, *self.neg]

    @property
    def columns(self) -> list[str]:
        return ["n", "n_pos", "xmin", "xmax", *self.s, *self.l, *self.split, *self.neg]


def clean(x: Column) -> Column:
    """The value as a double, NULL where it is no finite number."""
    x = x.cast("double")
    return F.when(~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))), x)


def accumulate(x: Column, spec: SummarySpec = SummarySpec()) -> list[Column]:
    """Aggregate expressions that build a summary from raw values; powers are products, so each is one multiplication.

    ``x`` should be a plain column (see ``prepared``): then Spark shares its common sub-expressions.
    """
    out = [F.count(x).alias("n"), _times((x + spec.shift if spec.log_policy == "shift" else x) > 0).alias("n_pos"), F.min(x).alias("xmin"), F.max(x).alias("xmax")]
    if spec.split:
        out += [_times(x < 0).alias("n_neg"), F.min(F.when(x > 0, x)).alias("pmin"), F.max(F.when(x < 0, x)).alias("nmax")]
    for family, base in ((spec.s, x), (spec.l, _log(x, spec)), (spec.neg, F.when(x < 0, F.ln(-x)))):
        power = base
        for name in family:
            out.append(F.coalesce(F.sum(power), F.lit(0.0)).alias(name))
            power = power * base
    return out


def _times(condition: Column) -> Column:
    """Rows for which the condition holds. (count_if names a common expression anew for every use, which keeps equal exchanges from being reused.)"""
    return F.count(F.when(condition, F.lit(1)))


def _log(x: Column, spec: SummarySpec) -> Column:
    y = x + F.lit(spec.shift) if spec.log_policy == "shift" else x
    return F.when(y > 0, F.ln(y))


def merge(spec: SummarySpec = SummarySpec()) -> list[Column]:
    """Aggregate expressions that merge summary rows: additions and two comparisons."""
    add = lambda c: F.coalesce(F.sum(c), F.lit(0 if c.startswith("n") else 0.0))
    return [(F.min(c) if c in _LEAST else F.max(c) if c in _MOST else add(c)).alias(c) for c in spec.columns]


def summarise(df: DataFrame, x: Column, by: list = (), spec: SummarySpec = SummarySpec()) -> DataFrame:
    df = df.withColumn("__x", clean(x))
    return df.groupBy(*by).agg(*accumulate(F.col("__x"), spec))


def merge_groups(cells: DataFrame, by: list = (), spec: SummarySpec = SummarySpec()) -> DataFrame:
    return cells.groupBy(*by).agg(*merge(spec))


def empty(spec: SummarySpec = SummarySpec()) -> list[Column]:
    zero = lambda c: F.lit(0).cast("long") if c in ("n", "n_pos", "n_neg") else F.lit(None).cast("double") if c in (*_LEAST, *_MOST) else F.lit(0.0)
    return [zero(c).alias(c) for c in spec.columns]


def as_struct(spec: SummarySpec = SummarySpec()) -> Column:
    """The columns of a summary as one struct, for functions that take a whole state. Absent families are empty arrays."""
    arr = lambda names: F.array(*map(F.col, names)) if names else F.array().cast("array<double>")
    own = lambda c, kind: (F.col(c) if c in spec.split else F.lit(None)).cast(kind).alias(c)
    shift = F.lit(float(spec.shift) if spec.log_policy == "shift" else 0.0).alias("shift")
    return F.struct(
        F.col("n").alias("n"), F.col("n_pos").alias("n_pos"), F.col("xmin").alias("xmin"), F.col("xmax").alias("xmax"), arr(spec.s).alias("s"), arr(spec.l).alias("l"),
        shift, own("n_neg", "long"), own("pmin", "double"), own("nmax", "double"), arr(spec.neg).alias("m"))


def merge_pair(a: Column, b: Column) -> Column:
    """Merge of two states held in one row; NULL if both are, else a NULL state is the neutral element. Logs of different shifts don't add up: they go."""
    add = lambda f: F.zip_with(a[f], b[f], lambda x, y: x + y)
    logs = lambda f: F.when(a["shift"] == b["shift"], add(f)).otherwise(F.array().cast("array<double>"))
    both = F.struct(
        (a["n"] + b["n"]).alias("n"), (a["n_pos"] + b["n_pos"]).alias("n_pos"), F.least(a["xmin"], b["xmin"]).alias("xmin"), F.greatest(a["xmax"], b["xmax"]).alias("xmax"),
        add("s").alias("s"), logs("l").alias("l"), a["shift"].alias("shift"), (a["n_neg"] + b["n_neg"]).alias("n_neg"), F.least(a["pmin"], b["pmin"]).alias("pmin"), F.greatest(a["nmax"], b["nmax"]).alias("nmax"), add("m").alias("m"))
    return F.when(a.isNull(), b).when(b.isNull(), a).otherwise(both)


def subtract_pair(a: Column, b: Column, xmin: Column, xmax: Column) -> Column:
    """a without b: sums are taken off; extremes can't be undone and come from the caller (inner ends of a split stay a's, which hold what is left)."""
    less = lambda f: F.zip_with(a[f], b[f], lambda x, y: x - y).alias(f)
    return F.struct(
        (a["n"] - b["n"]).alias("n"), (a["n_pos"] - b["n_pos"]).alias("n_pos"), xmin.alias("xmin"), xmax.alias("xmax"), less("s"), less("l"),
        a["shift"].alias("shift"), (a["n_neg"] - b["n_neg"]).alias("n_neg"), a["pmin"].alias("pmin"), a["nmax"].alias("nmax"), less("m"))


def means(spec: SummarySpec = SummarySpec()) -> list[Column]:
    """Running-mean form, derived from the sums after aggregation."""
    return [(F.col(c) / F.col("n")).alias(f"mean_{c}") for c in [*spec.s, *spec.l]]


def nbytes(spec: SummarySpec = SummarySpec()) -> int:
    """Theoretical size: order sums of each family kept, count and extremes (and what a split needs), eight bytes each."""
    return 8 * (len(spec.s) + len(spec.l) + len(spec.neg) + len(spec.split) + 3)


def roots(spec: SummarySpec = SummarySpec(), digits: int = 4) -> list[Column]:
    """Signed i-th roots of the moments: comparable between engines whatever the order of additions."""
    out = []
    for names in (spec.s, spec.l):
        for i, c in enumerate(names, 1):
            m = F.col(c) / F.col("n")
            out.append(F.round(F.signum(m) * F.pow(F.abs(m), F.lit(1.0 / i)), digits).alias(f"r_{c}"))
    return out


_HEAD = "<BBBBqqdddqdd"


def pack(state) -> bytes:
    """Little-endian interchange form: version, orders of the three families, counts, extremes, shift, the split's count and ends, sums."""
    fields = state.asDict() if hasattr(state, "asDict") else dict(state)
    s, l, m = (list(fields.get(f) or []) for f in ("s", "l", "m"))
    real = lambda c: float("nan") if fields.get(c) is None else fields[c]
    n_neg = -1 if fields.get("n_neg") is None else fields["n_neg"]
    return struct.pack(f"{_HEAD}{len(s) + len(l) + len(m)}d", 2, len(s), len(l), len(m), fields["n"], fields["n_pos"], real("xmin"), real("xmax"), fields.get("shift") or 0.0, n_neg, real("pmin"), real("nmax"), *s, *l, *m)


def unpack(data: bytes) -> dict:
    version, k, q, r, n, n_pos, lo, hi, shift, n_neg, pmin, nmax = struct.unpack_from(_HEAD, data)
    if version != 2:
        raise ValueError(f"unknown version {version}")
    rest = list(struct.unpack_from(f"<{k + q + r}d", data, struct.calcsize(_HEAD)))
    gone = lambda v: None if v != v else v
    return {
        "n": n, "n_pos": n_pos, "xmin": gone(lo), "xmax": gone(hi), "s": rest[:k], "l": rest[k : k + q], "shift": shift,
        "n_neg": None if n_neg < 0 else n_neg, "pmin": gone(pmin), "nmax": gone(nmax), "m": rest[k + q :]}
