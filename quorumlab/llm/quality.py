"""Quality classifier: a sparse ensemble of rules over text statistics.

1. Statistics of every whole text (shape of words, kinds of characters, repetition) are taken in one scan.
2. Shallow boosted trees are fitted to a bounded, hash-ordered sample of labelled rows; each node's path
   from the root is a rule, a conjunction of comparisons.
3. A logistic model with an L1 penalty weighs the rules (and an intercept); most weights become zero.
4. The surviving rules are compiled into Spark column expressions, and scoring is a projection.

Labels are read only of rows outside the held-out fold: crc32 of the id as text, modulo 3, is not 1. Ids, sources and
languages are never inputs of a score.

Defined cases: a null text counts as empty and is scored like any other; without labels, or with
labels of one kind only, every score is the smoothed share of label 1; labels that are null are not used; repeated
rows have a result each.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

#: Most labelled rows that a model is fitted to (they come to the driver as numbers).
SAMPLE_ROWS = 20_000
TREES, DEPTH, BINS, SHRINK, LEAST_LEAF = 40, 3, 32, 0.3, 10
#: L1 strengths tried, as shares of the smallest one that makes all weights zero.
PENALTIES = (0.1, 0.03, 0.01, 0.003)
SWEEPS = 300

STATISTICS = [
    "n_chars", "n_words", "word_length", "upper_share", "digit_share", "mark_share", "symbol_share", "pipe_share", "other_byte_share",
    "shout_words", "shout_share", "repeat_words", "repeat_share", "distinct_share", "top_share", "line_repeat_share", "marked_words_share",
    "line_words", "worst_line_marks", "worst_line_shout", "longest_word", "space_share", "worst_line_same", "end_marks_share",
]


def statistics(body: bytes) -> list[float]:
    """The statistics of one text, in the order of STATISTICS."""
    from collections import Counter

    import numpy as np

    n = len(body)
    if not n:
        return [0.0] * len(STATISTICS)
    counts = np.bincount(np.frombuffer(body, np.uint8), minlength=256)
    chars = n - int(counts[0x80:0xC0].sum())
    words = body.split()
    m = max(1, len(words))
    upper, digits = int(counts[65:91].sum()), int(counts[48:58].sum())
    letters = max(1, upper + int(counts[97:123].sum()))
    marks = int(counts[33:48].sum() + counts[58:65].sum() + counts[91:97].sum() + counts[123:127].sum())
    symbols = int(counts[[35, 36, 37, 38, 42, 33]].sum())
    shout = sum(map(bytes.isupper, words))
    repeats = sum(map(bytes.__eq__, words, words[1:]))
    kinds = Counter(words)
    lines = [x for x in body.split(b"\n") if x]
    worst_marks = worst_shout = worst_same = 0.0
    for line in lines:
        inside = line.split()
        if len(inside) >= 4:
            worst_same = max(worst_same, 1 - len(set(inside)) / len(inside))
            worst_shout = max(worst_shout, sum(map(bytes.isupper, inside)) / len(inside))
            bad = len(line) - len(line.translate(None, b"#$%&*!|"))
            worst_marks = max(worst_marks, bad / len(line))
    ends = sum(w[-1:] in b"#$%&*!|" for w in words)
    return [
        float(chars), float(len(words)), (n - int(counts[[9, 10, 11, 12, 13, 32]].sum())) / m, upper / letters, digits / n, marks / n, symbols / n, int(counts[124]) / m, int(counts[128:].sum()) / n,
        float(shout), shout / m, float(repeats), repeats / m, len(kinds) / m, kinds.most_common(1)[0][1] / m if words else 0.0, 1 - len(set(lines)) / max(1, len(lines)), ends / m,
        m / max(1, len(lines)), worst_marks, worst_shout, float(max(map(len, words), default=0)), int(counts[32]) / n, worst_same, sum(w[-2:] == b"!!" for w in words) / m,
    ]


def _measure(batches: Iterator) -> Iterator:
    import pyarrow as pa

    for batch in batches:
        rows = [statistics(v.as_py() or b"") for v in batch.column(1)]
        columns = list(zip(*rows, strict=True)) if rows else [[] for _ in STATISTICS]
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, pa.float64()) for c in columns)], names=["doc_id", *STATISTICS])


def measure(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    body = docs.select(F.col(key).cast("bigint").alias("doc_id"), F.col(text).cast("binary").alias("body"))
    return body.mapInArrow(_measure, "doc_id bigint, " + ", ".join(f"{s} double" for s in STATISTICS))


# --- fitting, on the driver, from the bounded sample ----------------------------------------------------------

Rule = tuple[tuple[int, bool, float], ...]  # (statistic, above, threshold): above means value > threshold


def _grow(binned, cuts, gradient, hessian, rows, depth: int, path: Rule, rules: set, predict) -> None:
    """One boosted tree, splitting on the best second-order gain; every path below the root becomes a rule."""
    import numpy as np

    g, h = gradient[rows].sum(), hessian[rows].sum()
    best = (1e-6, None)
    if depth:
        for f in range(binned.shape[1]):
            b = binned[rows, f]
            gs = np.bincount(b, gradient[rows], BINS)[:-1].cumsum()
            hs = np.bincount(b, hessian[rows], BINS)[:-1].cumsum()
            ns = np.bincount(b, minlength=BINS)[:-1].cumsum()
            gain = gs**2 / (hs + 1) + (g - gs) ** 2 / (h - hs + 1) - g**2 / (h + 1)
            gain[(ns < LEAST_LEAF) | (len(rows) - ns < LEAST_LEAF)] = -1
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (gain[k], (f, k))
    if best[1] is None:
        predict[rows] += -SHRINK * g / (h + 1)
        return
    f, k = best[1]
    for above in (False, True):
        part = rows[(binned[rows, f] > k) == above]
        rule = (*path, (f, above, float(cuts[f][k])))
        rules.add(tuple(sorted(rule)))
        _grow(binned, cuts, gradient, hessian, part, depth - 1, rule, rules, predict)


def grow_rules(x, y) -> list[Rule]:
    import numpy as np

    cuts = []
    for f in range(x.shape[1]):
        q = np.unique(np.quantile(x[:, f], np.linspace(0, 1, BINS + 1)[1:-1]))
        cuts.append(np.concatenate([q, np.full(BINS - len(q), np.inf)]))
    binned = np.stack([np.minimum(np.searchsorted(cuts[f], x[:, f], "left"), BINS - 1) for f in range(x.shape[1])], axis=1)
    rules: set[Rule] = set()
    predict = np.full(len(y), math.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3)))
    rng = np.random.Generator(np.random.PCG64(5))
    for _ in range(TREES):
        p = 1 / (1 + np.exp(-predict))
        rows = np.flatnonzero(rng.random(len(y)) < 0.7)
        _grow(binned, cuts, p - y, p * (1 - p), rows, DEPTH, (), rules, predict)
    return sorted(rules)


def apply_rules(rules: list[Rule], x):
    import numpy as np

    out = np.ones((len(x), len(rules)))
    for k, rule in enumerate(rules):
        for f, above, cut in rule:
            out[:, k] *= (x[:, f] > cut) == above
    return out


def lasso_logistic(r, y, penalty: float):
    """(intercept, weights) by accelerated proximal gradient; the intercept isn't penalised."""
    import numpy as np

    n = len(y)
    step = 4 * n / (np.linalg.norm(r, 2) ** 2 + n)
    w, b = np.zeros(r.shape[1]), math.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6))
    vw, vb, t = w, b, 1.0
    for _ in range(SWEEPS):
        e = 1 / (1 + np.exp(-(r @ vw + vb))) - y
        nw = vw - step * (r.T @ e) / n
        nw = np.sign(nw) * np.maximum(np.abs(nw) - step * penalty, 0)
        nb = vb - step * e.mean()
        s = (1 + math.sqrt(1 + 4 * t * t)) / 2
        vw, vb = nw + (t - 1) / s * (nw - w), nb + (t - 1) / s * (nb - b)
        w, b, t = nw, nb, s
    return b, w


@dataclass(frozen=True)
class RuleModel:
    intercept: float
    rules: tuple[tuple[float, Rule], ...]  # weight and conjunction

    def score(self) -> Column:
        """The model as a column over the statistics: 1 / (1 + exp(-(intercept + sum of weights of rules that hold)))."""
        total = F.lit(self.intercept)
        for weight, rule in self.rules:
            holds = F.lit(True)
            for f, above, cut in rule:
                c = F.col(STATISTICS[f])
                holds = holds & ((c > cut) if above else (c <= cut))
            total = total + F.when(holds, F.lit(weight)).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-total))

    def describe(self) -> list[str]:
        said = lambda rule: " and ".join(f"{STATISTICS[f]} {'>' if above else '<='} {cut:.4g}" for f, above, cut in rule)
        return [f"{w:+.3f} if {said(rule)}" for w, rule in sorted(self.rules, key=lambda x: -abs(x[0]))]


def fit(x, y) -> RuleModel:
    import numpy as np

    if not len(y) or y.min() == y.max():
        share = (float(y.sum()) + 1) / (len(y) + 2)
        return RuleModel(math.log(share / (1 - share)), ())
    rules = grow_rules(x, y)
    r = apply_rules(rules, x)
    if not rules:
        return RuleModel(lasso_logistic(np.zeros((len(y), 1)), y, 1.0)[0], ())
    top = float(np.abs(r.T @ (y.mean() - y)).max()) / len(y)
    fold = np.arange(len(y)) % 4 == 0
    tried = []
    for p in PENALTIES:  # chosen on a fourth of the sample, then fitted to all of it
        b, w = lasso_logistic(r[~fold], y[~fold], p * top)
        z = r[fold] @ w + b
        tried.append((float(np.logaddexp(0, np.where(y[fold] == 1, -z, z)).mean()), p))
    b, w = lasso_logistic(r, y, min(tried)[1] * top)
    return RuleModel(float(b), tuple((float(v), rule) for v, rule in zip(w, rules, strict=True) if abs(v) > 1e-6))


def held_out(key: Column) -> Column:
    return F.crc32(key.cast("string").cast("binary")) % 3 == 1


def train(measured: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> RuleModel:
    """Fit to at most ``sample_rows`` labelled rows outside the held-out fold, the first by a hash of the id."""
    import numpy as np

    usable = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    ids = usable.groupBy(F.col("doc_id").alias("_id")).agg(F.max("quality").alias("_label")).orderBy(F.xxhash64(F.col("_id")), "_id").limit(sample_rows)
    sample = measured.join(F.broadcast(ids), F.col("doc_id") == F.col("_id")).select("_id", "_label", *STATISTICS).dropDuplicates(["_id"])
    rows = sorted(map(tuple, sample.collect()))
    data = np.array([r[1:] for r in rows], np.float64).reshape(len(rows), 1 + len(STATISTICS))
    return fit(data[:, 1:], (data[:, 0] > 0).astype(np.float64))


def classify(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted."""
    measured = written(measure(docs, key, text), "statistics")
    model = train(measured, labels)
    score = model.score()
    out = measured.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), score.alias("score"))
    return out.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))
