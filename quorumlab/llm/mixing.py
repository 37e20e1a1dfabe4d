"""Soft-membership mixing: document rates whose expected domain totals match target weights.

1. A naive Bayes classifier is learned from a labelled table: which distinct words and shape tags a document has, for each
   domain. It gives every document a posterior over the domains; a document belongs to all of them in part.
2. Rates: each document gets a rate r >= 0, its expected number of copies. With t tokens and posterior p, the totals
   T[k] = sum of r t p[k] should equal the targets. Projected gradient descent solves this least-squares problem,
   starting from rate 1. The gradient needs only the K totals, one aggregate over all documents; a document's rate is a function of
   its posterior and of the few gradients so far, so rates are recomputed as an expression and never stored or joined.
   Residuals are weighed by the inverse of sum t p p', with which a step of length one always converges.
3. Copies: the whole part of the rate, and one more with the fraction as probability, decided by a hash of the id.

Only DataFrame operations run on the data. The driver sees K-vectors and the classifier's table
(at most ``features`` rows).

Defined cases: null and empty texts, and those of marks alone, have no words and no tokens, the prior as posterior, and never change a total; a null id has a
rate, and is hashed as one key; labels that name no domain are not used; a domain without labelled rows gets no posterior
mass and its target cannot be met, which ``domain_totals`` reports; without any labels all domains are equally likely;
repeated rows are separate documents.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import drop_written, spare, unit_hash, written

#: Most labelled rows that the classifier is fitted to, and most features it keeps.
SAMPLE_ROWS, FEATURES = 20_000, 128
#: Least labelled documents that have a feature.
LEAST_DOCS = 5
#: How many times likelier a feature must be in some domain than in the others together.
LEAST_LIFT = 3.0
#: Descent ends once every domain's share is this close to its target, or no rate moves. ``domain_totals`` tells what is left.
ITERATIONS, TOLERANCE = 50, 1e-4
#: Cut points of the shape tags.
CUTS = {"marked": (0.0, 0.05, 0.2, 0.5), "capital": (0.05, 0.2, 0.5), "distinct": (0.2, 0.4, 0.55, 0.7, 0.85)}
#: What parts words, marks at the end of a run of characters, and runs of capitals.
SEPARATORS = r"[\x20\x09-\x0D.,;:?!#$%&*|]+"
MARKED = r"[#$%&*!|](?=[\x20\x09-\x0D]|$)"
CAPITALS = r"(?<![^\x20\x09-\x0D])[A-Z]{2,}"

#: The default domains of the labels table, and their target shares of all tokens.
TARGETS = {"clean": 0.90, "junk": 0.06, "toxic": 0.04}


def label_domain() -> Column:
    return F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 0, "junk").when(F.col("quality") == 1, "clean")


def word_array(text: Column) -> Column:
    """The words of a text, lowered: runs of characters other than white space and marks."""
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), SEPARATORS), "")


def _tag(share: Column, name: str) -> Column:
    """array(" name k"), k counting the cuts below the share. Words hold no space, so a tag is never a word."""

    def of(v: Column) -> Column:
        out = F.lit(f" {name} {len(CUTS[name])}")
        for k, cut in reversed(list(enumerate(CUTS[name]))):
            out = F.when(v <= cut, f" {name} {k}").otherwise(out)
        return out

    return F.transform(F.array(share), of)


def feature_array(text: Column, words: Column) -> Column:
    """Distinct words, and one tag for each shape. Shapes are counted in the text, which is cheaper than looking at each word."""
    n, distinct = F.greatest(F.size(words), F.lit(1)), F.array_distinct(words)
    shares = {"marked": F.regexp_count(text, F.lit(MARKED)) / n, "capital": F.regexp_count(text, F.lit(CAPITALS)) / n, "distinct": F.size(distinct) / n}
    # Each share is computed once, as a lambda's argument.
    tags = [_tag(shares[name], name) for name in CUTS]
    return F.concat(distinct, *tags)


@dataclass(frozen=True)
class DomainModel:
    domains: tuple[str, ...]
    base: tuple[float, ...]  # log prior plus log-probabilities of having none of the features
    gain: dict[str, tuple[float, ...]]  # feature -> what its presence adds, for each domain
    prior: tuple[float, ...]

    def posterior(self, text: Column, words: Column) -> Column:
        """array<double> over the domains, from a text and its words."""
        total = F.array(*[F.lit(b) for b in self.base])
        if self.gain:
            names = sorted(self.gain)
            keys = F.array(*[F.lit(x) for x in names])
            values = F.array(*[F.array(*[F.lit(v) for v in self.gain[x]]) for x in names])
            present = F.array_intersect(feature_array(text, words), keys)
            gains = F.map_from_arrays(keys, values)
            total = F.aggregate(present, total, lambda acc, f: F.zip_with(acc, F.element_at(gains, f), lambda x, y: x + y))
        most = F.array_max
        scaled = F.transform(F.array(total), lambda s: F.transform(s, lambda v: F.exp(v - most(s))))[0]
        shares = F.transform(F.array(scaled), lambda e: F.transform(e, lambda v: v / F.aggregate(e, F.lit(0.0), lambda a, b: a + b)))[0]
        return F.when(F.size(words) > 0, shares).otherwise(F.array(*[F.lit(p) for p in self.prior]))


def learn_domains(docs: DataFrame, labelled: DataFrame, domains: list[str], sample_rows: int = SAMPLE_ROWS, features: int = FEATURES, key: str = "doc_id", text: str = "text") -> DomainModel:
    """labelled: (doc_id, domain). Fits to at most ``sample_rows`` labelled documents, the first by a hash of the id."""
    k = len(domains)
    ids = labelled.where(F.col("domain").isin(domains) & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").alias("_id")).agg(F.min("domain").alias("_domain"))
    ids = ids.orderBy(F.xxhash64(F.col("_id")), "_id").limit(sample_rows)
    sample = docs.select(F.col(key).alias("_doc"), F.col(text).alias("text")).join(F.broadcast(ids), F.col("_doc") == F.col("_id"))
    sample = sample.select("_domain", "text", word_array(F.col("text")).alias("words")).where(F.size("words") > 0)
    sample = sample.select("_domain", F.explode(feature_array(F.col("text"), F.col("words"))).alias("feature"))
    each = [F.count_if(F.col("_domain") == d).alias(f"n{j}") for j, d in enumerate(domains)]
    counts = written(sample.groupBy("feature").agg(*each), "features")
    # Every document has exactly one tag of a kind, so these rows sum to the documents.
    totals = counts.where(F.col("feature").startswith(" distinct ")).agg(*[F.sum(f"n{j}") for j in range(k)]).first()
    size = [int(t or 0) for t in totals]
    everything = sum(size)
    if not everything:
        even = tuple([1.0 / k] * k)
        return DomainModel(tuple(domains), tuple(math.log(p) for p in even), {}, even)
    all_n = sum((F.col(f"n{j}") for j in range(k)), F.lit(0))
    share = all_n / everything
    inside = [F.col(f"n{j}") / max(1, size[j]) for j in range(k)]
    outside = [(all_n - F.col(f"n{j}") + 0.5) / (everything - size[j] + 1) for j in range(k)]
    # Only what points to a domain counts: common words differ with language and length, and not with the domain.
    points = F.greatest(*[i / o for i, o in zip(inside, outside, strict=True)]) if k > 1 else inside[0] / outside[0]
    z = [F.abs(i - share) * math.sqrt(n) / F.sqrt(share * (1 - share) + 1e-9) for i, n in zip(inside, size, strict=True)]
    best = F.greatest(*z) if k > 1 else z[0]
    kept = counts.where((all_n >= LEAST_DOCS) & (points >= LEAST_LIFT)).orderBy(best.desc(), "feature").limit(features).collect()
    drop_written(counts)
    prior = tuple((s + 1e-9) / (everything + k * 1e-9) for s in size)
    base, gain = [math.log(p) for p in prior], {}
    for row in kept:
        odds = [(row[f"n{j}"] + 0.5) / (size[j] + 1) for j in range(k)]
        base = [b + math.log(1 - q) for b, q in zip(base, odds, strict=True)]
        gain[row["feature"]] = tuple(math.log(q) - math.log(1 - q) for q in odds)
    return DomainModel(tuple(domains), tuple(base), gain, prior)


def _solve(matrix: list[list[float]], right: list[float]) -> list[float]:
    """Gaussian elimination for a K x K system; a direction without weight gets no step."""
    n = len(right)
    rows = [list(r) + [b] for r, b in zip(matrix, right, strict=True)]
    scale = max((abs(v) for r in matrix for v in r), default=0.0) or 1.0
    for c in range(n):
        p = max(range(c, n), key=lambda r: abs(rows[r][c]))
        rows[c], rows[p] = rows[p], rows[c]
        if abs(rows[c][c]) < 1e-12 * scale:
            rows[c] = [0.0] * (n + 1)
            rows[c][c] = 1.0
        for r in range(n):
            if r != c and rows[r][c]:
                f = rows[r][c] / rows[c][c]
                rows[r] = [x - f * y for x, y in zip(rows[r], rows[c], strict=True)]
    return [rows[c][n] / rows[c][c] for c in range(n)]


def rate_column(posterior: list[Column], steps: list[list[float]], max_rate: float | None = None) -> Column:
    """Rates have no upper bound unless one is asked for."""
    rate = F.lit(1.0)
    for step in steps:
        move = sum((p * F.lit(g) for p, g in zip(posterior, step, strict=True)), F.lit(0.0))
        rate = F.greatest(F.lit(0.0), rate - move)
        rate = rate if max_rate is None else F.least(F.lit(max_rate), rate)
    return rate


def fit_rates(members: DataFrame, targets: list[float], iterations: int = ITERATIONS, tolerance: float = TOLERANCE, max_rate: float | None = None) -> list[list[float]]:
    """The gradient steps that lead from rate 1 to the fitted rates. members: tokens, p0 .. pK-1."""
    k = len(targets)
    p, t = [F.col(f"p{j}") for j in range(k)], F.col("tokens").cast("double")
    pairs = [(i, j) for i in range(k) for j in range(i, k)]
    gram = members.agg(*[F.sum(t * p[i] * p[j]) for i, j in pairs], F.sum(t)).first()
    total = gram[len(pairs)] or 0.0
    if not total:
        return []
    h = [[0.0] * k for _ in range(k)]
    for (i, j), v in zip(pairs, gram, strict=False):
        h[i][j] = h[j][i] = v / total
    weight = sum(targets)
    steps: list[list[float]] = []
    for _ in range(iterations):
        rate = rate_column(p, steps, max_rate)
        now = members.agg(*[F.sum(rate * t * p[j]) for j in range(k)]).first()
        off = [(now[j] or 0.0) / total - targets[j] / weight for j in range(k)]
        if max(map(abs, off)) <= tolerance:
            break
        steps.append(_solve(h, off))
        if max(map(abs, steps[-1])) < 1e-9:
            break
    return steps


@dataclass(frozen=True)
class Mixture:
    model: DomainModel
    steps: list[list[float]]
    max_rate: float | None = None

    def rate(self, posterior: Column) -> Column:
        return rate_column([posterior[j] for j in range(len(self.model.domains))], self.steps, self.max_rate)


def copies_of(rate: Column, key: Column) -> Column:
    whole = F.floor(rate)
    return (whole + (unit_hash(F.lit("copies"), key) < rate - whole).cast("bigint")).cast("bigint")


def memberships(docs: DataFrame, model: DomainModel, key: str = "doc_id", text: str = "text", tokens: str | None = None) -> DataFrame:
    """doc_id, tokens, p0 .. pK-1. ``tokens`` names a column with a document's count by some tokenizer; without one, words are counted."""
    k = len(model.domains)
    count = F.size("words") if tokens is None else F.coalesce("_tokens", F.lit(0))
    rows = docs.select(F.col(key).alias("doc_id"), F.col(text).alias("text"), word_array(F.col(text)).alias("words"), (F.lit(None) if tokens is None else F.col(tokens)).alias("_tokens"))
    rows = rows.select("doc_id", count.cast("bigint").alias("tokens"), model.posterior(F.col("text"), F.col("words")).alias("p"))
    return rows.select("doc_id", "tokens", *[F.col("p")[j].alias(f"p{j}") for j in range(k)])


def fit_mixture(docs: DataFrame, labelled: DataFrame, targets: dict[str, float], key: str = "doc_id", text: str = "text", tokens: str | None = None) -> tuple[Mixture, DataFrame]:
    """The fitted mixture and the written memberships (doc_id, tokens, p0 .. pK-1)."""
    model = learn_domains(docs, labelled, list(targets), key=key, text=text)
    members = written(memberships(docs, model, key, text, tokens), "memberships")
    return Mixture(model, fit_rates(members, list(targets.values()))), members


def domain_totals(mixture: Mixture, members: DataFrame, targets: dict[str, float], tolerance: float = TOLERANCE) -> DataFrame:
    """domain, target, expected (shares of the tokens before mixing), residual, met: K rows that tell whether the targets are reached."""
    k, weight = len(targets), sum(targets.values())
    p, t = [F.col(f"p{j}") for j in range(k)], F.col("tokens").cast("double")
    rate = rate_column(p, mixture.steps, mixture.max_rate)
    sums = members.agg(*[F.sum(rate * t * p[j]).alias(f"s{j}") for j in range(k)], F.sum(t).alias("total"))
    rows = F.array(*[F.struct(F.lit(d).alias("domain"), F.lit(v / weight).alias("target"), F.coalesce(F.col(f"s{j}") / F.nullif(F.col("total"), F.lit(0.0)), F.lit(0.0)).alias("expected")) for j, (d, v) in enumerate(targets.items())])
    rows = sums.select(F.inline(rows)).withColumn("residual", F.col("expected") - F.col("target"))
    return rows.withColumn("met", F.abs("residual") <= tolerance)


def mixing_report(docs: DataFrame, labels: DataFrame, targets: dict[str, float] | None = None) -> DataFrame:
    """doc_id, tokens, one posterior column for each domain, rate, copies."""
    targets = targets or TARGETS
    mixture, members = fit_mixture(docs, labels.select("doc_id", label_domain().alias("domain")), targets)
    p = [F.col(f"p{j}") for j in range(len(targets))]
    rate = rate_column(p, mixture.steps, mixture.max_rate)
    out = members.select("doc_id", "tokens", *[c.alias(f"p_{d}") for c, d in zip(p, targets, strict=True)], rate.alias("rate"))
    return out.withColumn("copies", copies_of(F.col("rate"), F.col("doc_id")))


def mix(docs: DataFrame, labels: DataFrame, targets: dict[str, float] | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents, each as often as its rate decides; all columns kept, nothing shuffled."""
    mixture, members = fit_mixture(docs, labels.select("doc_id", label_domain().alias("domain")), targets or TARGETS, key, text)
    drop_written(members)
    names = docs.columns
    p, copy, words = spare(docs, "_p", "_copy", "_words")
    rated = docs.withColumn(words, word_array(F.col(text)))
    rated = rated.withColumn(p, mixture.model.posterior(F.col(text), F.col(words)))
    # No filter on the copies: it would be pushed below the posterior and compute it once more for each use.
    copies = copies_of(mixture.rate(F.col(p)), F.col(key)).cast("int")
    return rated.select(*names, F.explode(F.array_repeat(F.lit(1), copies)).alias(copy)).select(*names)
