"""Soft-membership mixing of documents to target weights of domains.

A labelled table teaches a classifier (independent normal features per domain) that gives every document a
posterior over domains.  Nonnegative rates per document are then fitted so that the expected tokens of each domain meet its
target: least squares over domains, by projected gradient steps.  The squares are weighed by the inverse of the domains' Gram
matrix, which makes 1 the step of the gradient and a few steps enough.  A step needs one sum per domain
over the whole table; a document's rate follows from its posterior and the history of these sums, so no step shuffles
documents.  Texts are read once; what follows works on a few numbers per document.  DataFrame functions only.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from math import log, pi

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .linefreq import _words
from .runtime import drop_table, let, materialise

#: Target shares of tokens by label value, and the label that keeps its present expected tokens.
TARGETS, ANCHOR = {"1": 0.95, "0": 0.05}, "1"
STEPS = 25
#: Added to the Gram matrix, as a share of its largest entry, so that equal domains stay solvable.
RIDGE = 1e-9
#: Steps between two writes of the per-document state of the fit.
WRITE_EVERY = 10
#: The fit ends when no domain is further from its target than this share of all tokens.
CLOSE = 1e-6
LEAST_VARIANCE = 1e-4


def features(text: Column) -> Column:
    """Struct of a token count and the feature array of a text."""

    def made(words: Column) -> Column:
        n = F.size(words)
        chars = F.length(F.array_join(words, ""))
        per = lambda count, of: F.when(of > 0, count / of).otherwise(F.lit(0.0))
        lines = F.split(text, "\n")
        return F.struct(
            n.cast("long").alias("n"),
            F.array(
                F.log1p(n.cast("double")), per(chars, n), per(F.size(F.array_distinct(words)), n), per(F.regexp_count(text, F.lit("[!#*$%&|<>]")), chars),
                per(F.regexp_count(text, F.lit("[0-9]")), chars), per(F.regexp_count(text, F.lit("[A-Z]")), chars), per(F.size(F.array_distinct(lines)), F.size(lines)),
            ).alias("x"),
        )

    return let(_words(text), made)


N_FEATURES = 7


@dataclass
class Mix:
    """A fitted mix; ``history`` holds the weighed residual of each step per domain, ``residuals`` the plain ones as shares of all tokens."""

    domains: list[str]
    prior: list[float] = field(default_factory=list)
    mean: list[list[float]] = field(default_factory=list)
    variance: list[list[float]] = field(default_factory=list)
    residuals: list[list[float]] = field(default_factory=list)
    history: list[list[float]] = field(default_factory=list)
    targets: list[float] = field(default_factory=list)

    def posterior(self, x: Column) -> Column:
        """Array of posteriors from a feature array."""
        if len(self.domains) < 2:
            return F.array(F.lit(1.0))

        def scores(x: Column) -> Column:
            out = []
            for p, mean, variance in zip(self.prior, self.mean, self.variance, strict=True):
                score = F.lit(log(p) - 0.5 * sum(log(2 * pi * v) for v in variance))
                for i, (m, v) in enumerate(zip(mean, variance, strict=True)):
                    score = score - (F.get(x, F.lit(i)) - m) * (F.get(x, F.lit(i)) - m) / (2 * v)
                out.append(score)
            return F.array(*out)

        def normal(s: Column) -> Column:
            top = F.array_max(s)
            total = lambda e: F.aggregate(e, F.lit(0.0), lambda a, b: a + b)
            return let(F.transform(s, lambda v: F.exp(v - top)), lambda e: F.transform(e, lambda v: v / total(e)))

        return let(let(x, scores), normal)

    def state(self, p: Column, start: Column, begin: int, end: int) -> Column:
        """The rate after steps ``begin`` to ``end`` of the history, from ``start``."""
        if begin >= end:
            return start
        steps = F.array(*(F.array(*map(F.lit, self.history[t])) for t in range(begin, end)))
        pull = lambda h: F.aggregate(F.zip_with(p, h, lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
        return F.aggregate(steps, start, lambda r, h: F.greatest(F.lit(0.0), r - pull(h)))

    def rate(self, p: Column) -> Column:
        return self.state(p, F.lit(1.0), 0, len(self.history))


def _solve(m: list[list[float]], v: list[float]) -> list[float]:
    """m x = v for a small positive matrix, by elimination with a ridge."""
    k = len(m)
    ridge = RIDGE * max(m[i][i] for i in range(k))
    a = [[*(m[i][j] + (ridge if i == j else 0.0) for j in range(k)), v[i]] for i in range(k)]
    for i in range(k):
        top = max(range(i, k), key=lambda r: abs(a[r][i]))
        a[i], a[top] = a[top], a[i]
        for r in range(k):
            if r != i:
                f = a[r][i] / a[i][i]
                a[r] = [x - f * y for x, y in zip(a[r], a[i], strict=True)]
    return [a[i][k] / a[i][i] for i in range(k)]


def feature_table(docs: DataFrame) -> DataFrame:
    """(doc_id, n, x) of every row, written once."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return materialise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), features(text).alias("f")).select("doc_id", "f.n", "f.x"), "features")


def classifier(table: DataFrame, labels: DataFrame, label: str) -> Mix:
    """Class means and variances in one aggregate over the labelled rows; classes are the label's values."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("string").alias("domain")).where("doc_id is not null and domain is not null").distinct()
    rows = table.join(known, "doc_id")
    flat = rows.select("domain", *(F.get("x", F.lit(i)).alias(f"x{i}") for i in range(N_FEATURES)))
    aggs = [f(f"x{i}").alias(f"{f.__name__}{i}") for i in range(N_FEATURES) for f in (F.avg, F.var_pop)]
    found = sorted(flat.groupBy("domain").agg(F.count("*").alias("n"), *aggs).collect(), key=lambda r: r["domain"])
    total = sum(r["n"] for r in found)
    mix = Mix([r["domain"] for r in found] or [""])
    for r in found:
        mix.prior.append(r["n"] / total)
        mix.mean.append([r[f"avg{i}"] for i in range(N_FEATURES)])
        mix.variance.append([max(LEAST_VARIANCE, r[f"var_pop{i}"]) for i in range(N_FEATURES)])
    return mix


def fit_mix(rows: DataFrame, labels: DataFrame, targets: dict[str, float] | None = None, anchor: str | None = ANCHOR, label: str = "quality", steps: int = STEPS) -> Mix:
    """Classifier, targets and rates from a feature table.

    A domain without a target keeps none; without an anchor all tokens are the budget.
    """
    targets = TARGETS if targets is None else targets
    mix = classifier(rows, labels, label)
    k = len(mix.domains)
    table = materialise(rows.where("n > 0").select("n", mix.posterior(F.col("x")).alias("p")), "posteriors")
    at = lambda i: F.get("p", F.lit(i))
    sums = table.agg(F.sum("n").alias("n"), *(F.sum(F.col("n") * at(i)).alias(f"t{i}") for i in range(k)), *(F.sum(F.col("n") * at(i) * at(j)).alias(f"m{i}_{j}") for i in range(k) for j in range(k))).first()
    if not sums["n"]:
        return mix
    n = float(sums["n"])
    present = [sums[f"t{i}"] / n for i in range(k)]
    if k == 1:
        mix.targets = present
        return mix
    weight = [targets.get(d, 0.0) for d in mix.domains]
    whole = sum(weight) or 1.0
    budget = 1.0
    if anchor in mix.domains and targets.get(anchor):
        i = mix.domains.index(anchor)
        budget = present[i] * whole / weight[i]
    mix.targets = [w / whole * budget for w in weight]
    gram = [[sums[f"m{i}_{j}"] / n for j in range(k)] for i in range(k)]
    held = table.select("n", "p", F.lit(1.0).alias("r"))
    written, behind = 0, None
    for t in range(steps):
        rate = mix.state(F.col("p"), F.col("r"), written, t)
        if t - written == WRITE_EVERY:
            fresh = materialise(held.select("n", "p", rate.alias("r")), "rates")
            if behind is not None:
                drop_table(behind)
            held = behind = fresh
            written, rate = t, F.col("r")
        got = held.select("n", "p", rate.alias("r")).agg(*(F.sum(F.col("n") * F.col("r") * at(i)).alias(f"t{i}") for i in range(k))).first()
        residual = [got[f"t{i}"] / n - mix.targets[i] for i in range(k)]
        mix.residuals.append(residual)
        if max(map(abs, residual)) < CLOSE:
            break
        mix.history.append(_solve(gram, residual))
    return mix


def _copies(rate: Column, doc_id: Column) -> Column:
    """Whole copies with the rate as their mean: the fraction decides by a hash of the id."""
    uniform = F.shiftrightunsigned(F.xxhash64(F.lit("mix"), doc_id), 11) / F.lit(float(1 << 53))
    return F.floor(rate + uniform).cast("long")


def mix_rates(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """(doc_id, n_tokens, domain, posterior, rate, copies) for each row of ``docs`` (doc_id, text, ...).

    Null and blank texts have no tokens and weigh nothing; they get the rate of their posterior.  Null ids and repeated rows get a
    row each.  Labels with nulls are left out; without labels there is one domain and every rate is 1.  Texts of any
    length are read whole; extra columns are not read; no documents give no rows.
    """
    table = feature_table(docs)
    mix = fit_mix(table, labels, **options)
    rows = table.select("doc_id", F.col("n").alias("n_tokens"), mix.posterior(F.col("x")).alias("posterior"))
    rows = rows.withColumn("rate", mix.rate(F.col("posterior")))
    best = F.array_position("posterior", F.array_max("posterior")).cast("int")
    domain = F.element_at(F.array(*map(F.lit, mix.domains)), best)
    return rows.select("doc_id", "n_tokens", domain.alias("domain"), "posterior", "rate", _copies(F.col("rate"), F.col("doc_id")).alias("copies"))


def mixed(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The rows of ``docs``, with all their columns, as many times as their copies say.

    Rows are written once with their features beside them, so no text is measured twice.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    row = F.struct(*(F.col(f"`{c}`") for c in docs.columns))
    rows = materialise(docs.select(row.alias("row"), F.col("doc_id").cast("long").alias("doc_id"), features(text).alias("f")), "measured")
    mix = fit_mix(rows.select("doc_id", "f.n", "f.x"), labels, **options)
    # the posterior is bound once, and no filter repeats the expression
    rate = let(mix.posterior(F.col("f.x")), mix.rate)
    repeats = F.array_repeat(F.lit(1), _copies(rate, F.col("doc_id")).cast("int"))
    return rows.select("row", F.explode(repeats)).select("row.*")
