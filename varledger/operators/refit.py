"""Approximate refits and the domain diagnostic of their fitted values."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TOL = 1e-6


def _products(df: DataFrame, terms: list[Column], y: Column, weight: Column | None = None) -> tuple[np.ndarray, np.ndarray, int]:
    """X'WX, X'Wy and rows, by one aggregate of k*k/2 sums."""
    x = [F.lit(1.0), *[t.cast("double") for t in terms]]
    w = F.lit(1.0) if weight is None else weight
    k = len(x)
    sums = [F.sum(w * x[i] * x[j]).alias(f"a{i}_{j}") for i in range(k) for j in range(i, k)]
    sums += [F.sum(w * x[i] * y).alias(f"b{i}") for i in range(k)]
    row = df.agg(*sums, F.count("*").alias("n")).first()
    a = np.zeros((k, k))
    for i in range(k):
        for j in range(i, k):
            a[i, j] = a[j, i] = row[f"a{i}_{j}"] or 0.0
    return a, np.array([row[f"b{i}"] or 0.0 for i in range(k)]), row.n


def _solve(a: np.ndarray, b: np.ndarray) -> np.ndarray | None:
    """None for a singular design, which is an unsuccessful fit."""
    scale = 1 / np.sqrt(np.maximum(np.diag(a), 1e-300))
    scaled = a * scale[:, None] * scale[None, :]
    if not np.isfinite(scaled).all() or np.linalg.cond(scaled) > 1e12:
        return None
    return np.linalg.solve(scaled, b * scale) * scale


def complete(df: DataFrame, columns: list[str]) -> DataFrame:
    """Rows on which all columns are present and finite."""
    out = df.select(*[F.col(c).cast("double").alias(c) for c in columns]).dropna()
    return out.where(" AND ".join(f"abs({c}) < double('infinity')" for c in columns))


def ols(df: DataFrame, y: str, terms: list[str]) -> dict | None:
    """Least squares with an intercept: coefficients by name, n and k."""
    rows = complete(df, [y, *terms])
    a, b, n = _products(rows, [F.col(t) for t in terms], F.col(y))
    beta = _solve(a, b)
    if beta is None:
        return None
    return {"coefficients": dict(zip(["intercept", *terms], beta.tolist(), strict=True)), "n": n, "k": len(terms) + 1}


def _linear(beta: np.ndarray, terms: list[str]) -> Column:
    eta = F.lit(float(beta[0]))
    for v, t in zip(beta[1:].tolist(), terms, strict=True):
        eta = eta + F.lit(v) * F.col(t)
    return eta


def fitted(fit: dict) -> Column:
    c = fit["coefficients"]
    terms = [t for t in c if t != "intercept"]
    return _linear(np.array([c["intercept"], *[c[t] for t in terms]]), terms)


def glm(df: DataFrame, y: str, terms: list[str], *, family: str, steps: int = 40, tol: float = 1e-9) -> dict | None:
    """poisson, quasipoisson, negbin (log link) or fraclogit (logit link) by
    weighted least squares, one aggregate a step.  Standard errors are of the
    sandwich form; dispersion is Pearson's over n - k, for negbin the moment
    estimate that the steps settle with."""
    rows = complete(df, [y, *terms]).persist()
    try:
        logit, alpha = family == "fraclogit", 0.0
        mean = rows.agg(F.avg(y)).first()[0]
        if mean is None or mean <= 0 or (logit and mean >= 1):
            return None
        beta = np.zeros(len(terms) + 1)
        beta[0] = np.log(mean / (1 - mean)) if logit else np.log(mean)
        for _ in range(steps):
            eta = _linear(beta, terms)
            mu = 1 / (1 + F.exp(-eta)) if logit else F.exp(eta)
            slope = mu * (1 - mu) if logit else mu
            w = slope / (1 + F.lit(alpha) * mu)
            a, b, n = _products(rows, [F.col(t) for t in terms], eta + (F.col(y) - mu) / slope, w)
            new = _solve(a, b)
            if new is None:
                return None
            moved = float(np.abs(new - beta).max())
            beta = new
            if family == "negbin":
                m = F.exp(_linear(beta, terms))
                s = rows.agg(F.sum((F.col(y) - m) ** 2 - m).alias("u"), F.sum(m * m).alias("v")).first()
                changed = max(0.0, s.u / s.v)
                moved = max(moved, abs(changed - alpha))
                alpha = changed
            if moved < tol:
                break
        eta = _linear(beta, terms)
        mu = 1 / (1 + F.exp(-eta)) if logit else F.exp(eta)
        variance = mu * (1 - mu) if logit else mu * (1 + F.lit(alpha) * mu)
        score = ((F.col(y) - mu) / (1 + F.lit(alpha) * mu)) ** 2
        meat, _, n = _products(rows, [F.col(t) for t in terms], F.lit(0.0), score)
        bread = np.linalg.inv(a)
        errors = np.sqrt(np.maximum(0, np.diag(bread @ meat @ bread)))
        pearson = rows.agg(F.sum((F.col(y) - mu) ** 2 / variance)).first()[0]
        names = ["intercept", *terms]
        return {
            "coefficients": dict(zip(names, beta.tolist(), strict=True)), "errors": dict(zip(names, errors.tolist(), strict=True)),
            "dispersion": alpha if family == "negbin" else pearson / max(n - len(names), 1), "n": n, "k": len(names),
        }
    finally:
        rows.unpersist()


def within(df: DataFrame, columns: list[str], keys: list[str]) -> DataFrame:
    """Columns less their mean in the group: fixed effects as a transform."""
    group = Window.partitionBy(*keys)
    return df.select(*keys, *[(F.col(c) - F.avg(c).over(group)).alias(c) for c in columns])


def outside(value: Column, domain: str, tol: float = TOL) -> Column:
    low = value < -tol
    return low if domain == "count" else low | (value > 1 + tol)


def violation_share(df: DataFrame, y: str, terms: list[str], fit: dict, domain: str) -> DataFrame:
    """Share of fitted values outside the domain; null where an observed
    response lies outside, since then the domain is not the response's."""
    rows = complete(df, [y, *terms])
    bad = F.count_if(outside(F.col(y), domain))
    share = F.avg(outside(fitted(fit), domain).cast("double"))
    return rows.agg(F.count("*").alias("n"), F.when(bad == 0, share).alias("share"))


SPEC = ["deposit_id", "estimator", "outcome", "code_file", "line_no"]


def plan(flags: DataFrame, commands: DataFrame, profiles: DataFrame, *, most: int = 8) -> DataFrame:
    """Fit specifications of flag records: SPEC, class, design, data_file, n_rows.

    Commands are those of the record's estimator on its outcome (``column``)
    that a refit accepts, with a readable design, the first ``most`` in file
    order.  The data file is the largest of the deposit that holds the response
    and every term, ties by name; without one there is no fit.
    """
    able = commands.where("NOT excluded AND design IS NOT NULL").select(
        "deposit_id", "estimator", F.col("column").alias("outcome"), F.col("file_id").alias("code_file"), "line_no", "design"
    ).distinct()
    order = Window.partitionBy("deposit_id", "estimator", "outcome").orderBy("code_file", "line_no")
    chosen = (
        flags.select("deposit_id", "estimator", "outcome", "class").join(able, ["deposit_id", "estimator", "outcome"])
        .withColumn("r", F.row_number().over(order)).where(F.col("r") <= most).drop("r")
    )
    names = F.flatten(F.transform("design", lambda t: F.split(F.regexp_replace(t, r"^i\.", ""), ":")))
    needed = chosen.withColumn("needed", F.array_distinct(F.concat(F.array("outcome"), names)))
    held = profiles.select("deposit_id", F.col("file_id").alias("data_file"), F.col("name").alias("need"), "n")
    in_file = needed.select(*SPEC, F.size("needed").alias("k"), F.explode("needed").alias("need")).join(held, ["deposit_id", "need"])
    whole = in_file.groupBy(*SPEC, "data_file", "k").agg(F.count("*").alias("have"), F.max("n").alias("n_rows")).where("have = k")
    best = whole.groupBy(*SPEC).agg(F.min(F.struct((-F.col("n_rows")).alias("o"), "data_file")).alias("b"))
    return chosen.join(best, SPEC).select(*SPEC, "class", "design", F.col("b.data_file").alias("data_file"), (-F.col("b.o")).alias("n_rows"))


def hash_cap(df: DataFrame, keys: list[str], n_rows: str, *, rows: int = 300_000) -> DataFrame:
    """At most ``rows`` rows of each group, those with the lowest hash of their
    content, given each group's size in ``n_rows``: a bounded sample that does
    not depend on the partitioning.  Of a larger group only the rows under a
    hash threshold a fifth above the cap are ranked, so no task sorts a group."""
    mark = F.xxhash64(*df.columns)
    spot = (F.shiftrightunsigned(mark, 11)).cast("double") / float(1 << 53)
    large = df.where(F.col(n_rows) > rows).withColumn("_h", mark).where(spot < 1.2 * rows / F.col(n_rows))
    order = Window.partitionBy(*keys).orderBy("_h", *df.columns)
    capped = large.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= rows).drop("_r", "_h")
    return df.where(F.coalesce(F.col(n_rows) <= rows, F.lit(True))).unionByName(capped)


def design_matrix(columns: dict[str, np.ndarray], design: list[str], *, most_levels: int = 300) -> np.ndarray | None:
    """Intercept and terms: plain columns, dummies of a factor but its first
    level, products; None beyond ``most_levels`` levels."""
    n = len(next(iter(columns.values())))
    out = [np.ones(n)]
    for term in design:
        if term.startswith("i."):
            levels, at = np.unique(columns[term[2:]], return_inverse=True)
            if len(levels) > most_levels:
                return None
            out += [(at == i).astype(float) for i in range(1, len(levels))]
        else:
            a, _, b = term.partition(":")
            out.append(columns[a] * columns[b] if b else columns[a])
    return np.column_stack(out)


def fit_rows(columns: dict[str, np.ndarray], outcome: str, design: list[str], domain: str, *, least: int = 30) -> dict:
    """One approximate refit over complete cases: status, n, k, n_outside."""
    names = {outcome, *(x for t in design for x in t.removeprefix("i.").split(":"))}
    ok = np.logical_and.reduce([np.isfinite(columns[c]) for c in names])
    used = {c: columns[c][ok] for c in names}
    y = used[outcome]
    n, out = len(y), {"n": int(ok.sum()), "k": None, "n_outside": None}
    if n < least:
        return out | {"status": "few_rows"}
    x = design_matrix(used, design)
    if x is None:
        return out | {"status": "many_levels"}
    out["k"] = x.shape[1]
    if n < 3 * x.shape[1]:
        return out | {"status": "few_rows"}
    if _outside(y, domain).any():
        return out | {"status": "response_outside"}
    size = np.sqrt((x * x).sum(0))
    if not size.all():
        return out | {"status": "singular"}
    scaled = x / size
    beta, _, rank, _ = np.linalg.lstsq(scaled, y, rcond=1e-10)
    if rank < x.shape[1]:
        return out | {"status": "singular"}
    return out | {"status": "fitted", "n_outside": int(_outside(scaled @ beta, domain).sum())}


def _outside(value: np.ndarray, domain: str, tol: float = TOL) -> np.ndarray:
    return value < -tol if domain == "count" else (value < -tol) | (value > 1 + tol)


FITS = ("deposit_id long, estimator string, outcome string, code_file string, line_no int, class string, data_file string, "
        "formula string, status string, n long, k long, n_outside long, share double")


def fit_all(specs: DataFrame, rows: DataFrame, *, cap: int = 300_000) -> DataFrame:
    """Every planned fit over the rows (deposit_id, file_id, numeric columns) of
    its data file, at most ``cap`` of them; a task holds one fit's rows at a
    time.  Each record names formula, code location, data file and row scope
    (complete cases), with the share of fitted values outside the domain where
    the fit succeeded."""
    data = [c for c in rows.columns if c not in ("deposit_id", "file_id")]
    held = rows.select("deposit_id", F.col("file_id").alias("data_file"), *[F.col(c).cast("double").alias(f"x_{c}") for c in data])
    joined = hash_cap(specs.join(held, ["deposit_id", "data_file"]), SPEC, "n_rows", rows=cap)

    def run(table: pa.Table) -> pa.Table:
        first = {c: table.column(c)[0].as_py() for c in (*SPEC, "class", "data_file", "design")}
        columns = {c: table.column(f"x_{c}").to_numpy().astype(float) for c in data}
        got = fit_rows(columns, first["outcome"], first["design"], first["class"])
        share = got["n_outside"] / got["n"] if got["status"] == "fitted" else None
        formula = f"{first['outcome']} ~ {' + '.join(first.pop('design'))}"
        row = first | got | {"formula": formula, "share": share}
        return pa.Table.from_pylist([{k: row[k] for k in _FIT_TYPES.names}], schema=_FIT_TYPES)

    return joined.groupBy(*SPEC).applyInArrow(run, FITS)


_FIT_TYPES = pa.schema([
    ("deposit_id", pa.int64()), ("estimator", pa.string()), ("outcome", pa.string()), ("code_file", pa.string()), ("line_no", pa.int32()),
    ("class", pa.string()), ("data_file", pa.string()), ("formula", pa.string()), ("status", pa.string()), ("n", pa.int64()), ("k", pa.int64()),
    ("n_outside", pa.int64()), ("share", pa.float64()),
])


def grouped(df: DataFrame, keys: list[str], y: str, x: str, *, domain: str, least: int = 30) -> DataFrame:
    """One-term fits of all groups at once: one aggregate, then one pass for the
    shares.  Groups under ``least`` rows or three a parameter are left out."""
    rows = df.select(*keys, F.col(y).cast("double").alias("y"), F.col(x).cast("double").alias("x")).dropna()
    fits = rows.groupBy(*keys).agg(
        F.count("*").alias("n"), F.regr_slope("y", "x").alias("slope"), F.regr_intercept("y", "x").alias("intercept"),
        F.count_if(outside(F.col("y"), domain)).alias("bad"),
    ).where((F.col("n") >= max(least, 6)) & F.col("slope").isNotNull())
    value = F.col("intercept") + F.col("slope") * F.col("x")
    shares = rows.join(fits, keys).groupBy(*keys).agg(
        F.first("n").alias("n"), F.first("slope").alias("slope"), F.first("intercept").alias("intercept"),
        F.count_if(outside(value, domain)).alias("n_outside"), F.first("bad").alias("bad"),
    )
    return shares.withColumn("share", F.when(F.col("bad") == 0, F.col("n_outside") / F.col("n"))).drop("bad")


def summarise(fits: DataFrame, keys: list[str]) -> DataFrame:
    """Of each flag the largest share over its successful fits, and how many."""
    return fits.groupBy(*keys).agg(F.max("share").alias("share"), F.count("share").alias("n_fits"))


def report(summary: DataFrame, *, at: float = 0.01, by: list[str] | None = None) -> DataFrame:
    """Records with a fit, with violations at the cut-off and of any size, and
    of those at the cut-off the median and largest share."""
    above = F.when(F.col("share") >= at, F.col("share"))
    return summary.groupBy(*(by or [])).agg(
        F.count("share").alias("n_fitted"), F.count_if(F.col("share") >= at).alias("n_at"), F.count_if(F.col("share") > 0).alias("n_any"),
        F.round(F.median(above), 6).alias("median_share"), F.round(F.max(above), 6).alias("max_share"),
    )
