"""Sweeps over samples too many to give every task a copy: all runs go through their rounds together.

The pieces of each (split, workers) are packed once into blocks of numpy rows, a partition for each piece or for several, as there are
cores: a round is short, and each of its tasks costs some hundredths of a second. A round is then one job for all runs, which passes over the pieces, sums the measures of the round before, picks the rows that the round draws and runs the local
chains. A run whose next plan depends on those measures has its chains in a job of their own. A task holds a block and the drawn rows of
its piece, never the piece. The driver sees local models and sums only.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor
from itertools import groupby

from pyspark import RDD, StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.util import inheritable_thread_target

from quorumlab.operators import models, samples as tasks, training
from quorumlab.plans.runspec import RunSpec, should_stop

#: Rows of a block, and rows that are scored at a time (the network's patches take some 20 kB a row).
BLOCK_ROWS, CHUNK = 4096, 512
BLOCKS = "worker int, first bigint, n int, x_type string, y_type string, x binary, y binary"


def pack(batches: Iterator) -> Iterator:
    """Arrow batches in order of (worker, pos), as blocks of bytes, each of one piece. Entries that are single-precision numbers are stored as such."""
    import numpy as np
    import pyarrow as pa

    for b in batches:
        ends = [*(np.flatnonzero(np.diff(b.column("worker").to_numpy())) + 1).tolist(), b.num_rows]
        for at, end in ((k, min(k + BLOCK_ROWS, end)) for begin, end in zip([0, *ends], ends, strict=False) for k in range(begin, end, BLOCK_ROWS)):
            part = b.slice(at, end - at)
            x, y = part.column("x").flatten().to_numpy(zero_copy_only=False), part.column("y").to_numpy(zero_copy_only=False)
            short = x.astype("f4")
            x = short if (short == x).all() else x
            values = [part.column("worker")[0].as_py(), part.column("pos")[0].as_py(), len(y), x.dtype.str, y.dtype.str, np.ascontiguousarray(x).tobytes(), np.ascontiguousarray(y).tobytes()]
            names = [f.split()[0] for f in BLOCKS.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(values, (pa.int32(), pa.int64(), pa.int32(), pa.string(), pa.string(), pa.binary(), pa.binary()), strict=True)], names=names)


def blocks_of(rows: DataFrame, group: int) -> RDD:
    """(group, worker, first pos, x, y) from (worker, pos, x, y), which are sorted inside partitions."""

    def unpack(r):
        import numpy as np

        return group, r["worker"], r["first"], np.frombuffer(r["x"], r["x_type"]).reshape(r["n"], -1), np.frombuffer(r["y"], r["y_type"])

    return rows.select("worker", "pos", "x", "y").mapInArrow(pack, BLOCKS).rdd.map(unpack).persist(StorageLevel.MEMORY_AND_DISK)


class Run:
    """A run between its rounds: what :func:`training.run_py` keeps in its loop."""

    def __init__(self, nth: int, spec: RunSpec, group: int, dims: int, classes: int):
        self.nth, self.spec, self.group, self.model = nth, spec, group, training.make_model(spec, dims, classes)
        self.w, self.time, self.messages, self.log, self.done = self.model.init(spec.seed), 0.0, 0, [], False
        self.period, self.curve = training.Period(spec), training.Curvature()
        self.arrivals = training.Arrivals(spec, self.model) if spec.scheme in training.ASYNCHRONOUS else None
        self.round, self.trained, self.plans = 0, None, {}

    @property
    def active(self) -> bool:
        return not self.done and (self.trained is not None or self.round < self.spec.rounds)

    @property
    def scored(self) -> bool:
        """Is the round that was trained last to be evaluated?"""
        return self.trained is not None and (self.trained + 1) % self.spec.eval_every == 0

    @property
    def goes_on(self) -> bool:
        """Can the next round be planned before the last one's measures are known?"""
        return self.round < self.spec.rounds and not (self.scored and self.spec.scheme == "adaptive_period")

    def draws(self) -> dict[int, list[tuple[int, int, int]]]:
        """What each worker draws in the next round: (round, worker, step) of each mini-batch, the keys of its hash."""
        out: dict[int, list] = {}
        if self.arrivals:
            self.plans[self.round] = self.arrivals.due()
            for _, k, n in self.plans[self.round]:
                out.setdefault(k, []).append((n, k, 0))
            return out
        now = self.period.of(self.round)
        plan = training.round_py(self.spec, self.round, now)
        self.plans[self.round] = now, plan
        return {m: [(self.round, m, s) for s in range(n)] for m, n in enumerate(plan["draw"].tolist()) if n}

    def step(self, found: list[tuple]) -> None:
        """The next model, from (worker, mini-batches, result) of the round."""
        alpha, found = training.step_size_at(self.spec, self.round), sorted(found, key=lambda f: f[0])
        if self.arrivals:
            batches = {key[:2]: batch for _, _, result in found for key, batch in result}
            self.arrivals.apply(self.plans[self.round], lambda k, n: batches[n, k], alpha)
            self.w = self.arrivals.w
        else:
            self.w = training.next_model(self.spec, self.w, [f[2] for f in found], [f[1] for f in found], alpha)
        self.trained, self.round = self.round, self.round + 1

    def record(self, measures: dict) -> None:
        """The log row of the round that was trained last."""
        s, round_no, plan = self.spec, self.trained, self.plans.pop(self.trained)
        if self.arrivals:
            now, up, down, steps, before = 1, s.workers, s.workers, [1] * s.workers, self.time
            self.time = plan[-1][0]
            took = self.time - before
        else:
            now, plan = plan
            up, down, steps, took = int(plan["up"].sum()), plan["down"], plan["steps"].tolist(), plan["time"]
            self.time += took
        self.messages += up + down
        if "grad" in measures:
            g = measures.pop("grad")
            measures |= {"grad_sq": float(g @ g), "smooth": self.curve.see(self.w, g)}
        if "loss" in measures and not self.arrivals:
            self.period.learn(measures["loss"], self.time, round_no)
        row = training.log_row(s, round_no, now, took, self.time, up + down, self.messages, up, steps, measures)
        self.log.append(row)
        self.done, self.trained = should_stop(s, row), None


def chains(work: dict, blocks: Iterable) -> Iterator:
    """The local results (run, worker, mini-batches, result) of pieces, one after another. ``work``: sizes of the pieces, and the runs of each group."""
    for (group, worker), own in groupby(blocks, lambda b: b[:2]):
        yield from piece_chains(work, group, worker, own)


def piece_chains(work: dict, group: int, worker: int, blocks: Iterable) -> Iterator:
    """The same of one piece. Runs of one seed draw the same mini-batches in a round, so each is drawn and picked once for all of them."""
    import numpy as np

    runs = [(*run, keys) for *run, draws in work["runs"].get(group, []) if (keys := draws.get(worker, []))]
    named = sorted({(spec.batch, spec.seed, *key) for _, spec, _, _, _, keys in runs for key in keys})
    powers = {batch: tasks.draw_powers(batch) for batch, *_ in named}
    n, order = work["sizes"].get(group, {}).get(worker, 0), None
    for _, _, first, x, y in blocks:
        if order is None:
            at = np.concatenate([tasks.draws_py(*key, batch, n, powers[batch]) for batch, *key in named]) if named else np.zeros(0, np.int64)
            order = np.argsort(at, kind="stable")
            at = at[order]
            xs, ys = np.empty((len(at), x.shape[1])), np.empty(len(at), y.dtype)
        lo, hi = np.searchsorted(at, [first, first + len(y)])
        xs[order[lo:hi]], ys[order[lo:hi]] = x[at[lo:hi] - first], y[at[lo:hi] - first]
    begin, mine, place, together = 0, {}, {}, {}
    for batch, same in groupby(named, lambda k: k[0]):
        same = list(same)
        end = begin + batch * len(same)
        mine[batch] = xs[begin:end].reshape(len(same), batch, -1), ys[begin:end].reshape(len(same), batch)
        place |= {k: nth for nth, k in enumerate(same)}
        begin = end
    for nth, spec, model, w, alpha, keys in runs:
        (x, y), own = mine[spec.batch], [place[spec.batch, spec.seed, *key] for key in keys]
        batches = [(x[k], y[k]) for k in own]
        if spec.scheme in training.ASYNCHRONOUS:
            yield nth, worker, len(keys), list(zip(keys, batches, strict=True))
        elif spec.scheme in training.GRADIENTS:
            yield nth, worker, len(keys), models.gradients_at(model, w, batches)
        elif model.kind == "softmax":
            together.setdefault((spec.batch, model.classes), []).append((nth, len(keys), w, own[0], alpha))
        else:
            yield nth, worker, len(keys), models.local_chain(model, w, batches, alpha)
    for (batch, classes), own in together.items():
        nths, steps, ws, begins, alphas = zip(*own, strict=True)  # a run's steps follow one another
        x, y = mine[batch]
        results = models.softmax_chains(ws, x, y, begins, steps, alphas, x.shape[2], classes)
        yield from ((nth, worker, n, w) for nth, n, w in zip(nths, steps, results, strict=True))


def widen(entries: list) -> tuple:
    """(runs, models side by side) of the softmax models to score without gradients, and the other entries."""
    import numpy as np

    flat = [e for e in entries if e[1].kind == "softmax" and not e[3] and np.isfinite(e[2]).all()]
    if not flat:
        return [], None, 0, entries
    dims, classes = flat[0][1].dims, flat[0][1].classes
    wide = np.stack([w.reshape(dims, classes) for _, _, w, _ in flat], axis=2).reshape(dims, -1)
    return [e[0] for e in flat], wide, classes, [e for e in entries if not any(e is f for f in flat)]


def add_scores(total: dict, entries: tuple, test: bool, x, y) -> None:
    """Add a block to (run, held out) -> (rows, sum): correct rows of the held-out fold, else the loss and, where asked for, the gradient."""
    import numpy as np

    def add(nth: int, rows: int, v) -> None:
        n, s = total.get((nth, test), (0, 0.0))
        total[nth, test] = n + rows, s + v

    flat, wide, classes, rest = entries
    if flat:
        own = np.zeros(len(flat))
        for label in np.unique(y):
            same = x[y == label].astype(float)
            for at in range(0, len(same), CHUNK):
                own += models.softmax_scores(wide, same[at : at + CHUNK], int(label), classes, not test)
        for nth, v in zip(flat, own, strict=True):
            add(nth, len(y), np.array([v]))
    for at in range(0, len(y) if rest else 0, CHUNK):
        a, b = x[at : at + CHUNK].astype(float), y[at : at + CHUNK]
        for nth, model, w, gradient in rest:
            if test:
                v = np.array([(model.predict(w, a) == b).sum()], float)
            elif gradient:
                loss, g = model.loss_grad(w, a, b)
                v = np.concatenate([[loss], g]) * len(b)
            else:
                v = np.array([model.loss(w, a, b)]) * len(b)
            add(nth, len(b), v)


def one_pass(work: dict, blocks: Iterable) -> Iterator:
    """Over a partition: the local results (True, ...) of :func:`chains`, and the sums (False, run, held out, rows, sum) of measures."""
    total: dict = {}
    wide: dict = {}

    def scored():
        for block in blocks:
            group, _, _, x, y = block
            if group in work["score"]:
                if group not in wide:
                    wide[group] = widen(work["score"][group])
                add_scores(total, wide[group], group == TEST, x, y)
            yield block

    for found in chains(work, scored()):
        yield True, *found
    for key, (n, s) in total.items():
        yield False, *key, n, s


#: The group of the held-out fold, and how many groups are packed at a time.
TEST, SIDE_BY_SIDE = -1, 4


def sweep(spark: SparkSession, specs: list[RunSpec], samples: DataFrame, dims: int, classes: int, measures: tuple[str, ...]) -> list[dict]:
    """The log rows of all runs; measures that aren't named are null, and what they alone need isn't computed."""
    sc = spark.sparkContext
    base = samples.select("row_id", "x", "y").persist(StorageLevel.MEMORY_AND_DISK)
    groups = sorted({(s.split, s.workers) for s in specs})

    def pieces(g: int) -> tuple[RDD, dict[int, int]]:
        """The packed pieces of a group, and their rows."""
        split, workers = groups[g]
        shards = tasks.SPLITS[split](tasks.train_test(base, False), workers)
        parts = min(workers, sc.defaultParallelism)
        packed = blocks_of(shards.repartitionById(parts, F.col("worker") % parts).sortWithinPartitions("worker", "pos"), g)
        sizes: dict[int, int] = {}
        for worker, n in packed.map(lambda b: (b[1], len(b[4]))).collect():  # one number for each block
            sizes[worker] = sizes.get(worker, 0) + n
        return packed, sizes

    def held_out() -> RDD:
        rows = tasks.train_test(base, True).select(F.lit(-1).alias("worker"), F.lit(0).cast("bigint").alias("pos"), "x", "y")
        packed = blocks_of(rows.coalesce(sc.defaultParallelism), TEST)
        packed.count()
        return packed

    # Groups are packed side by side: one with few pieces keeps few cores busy.
    with ThreadPoolExecutor(max_workers=SIDE_BY_SIDE) as pool:
        packing = {g: pool.submit(inheritable_thread_target(spark)(pieces), g) for g in range(len(groups))}
        test = pool.submit(inheritable_thread_target(spark)(held_out))
        kept = {g: p.result()[0] for g, p in packing.items()} | {TEST: test.result()}
        sizes = {g: p.result()[1] for g, p in packing.items()}
    base.unpersist()
    runs = [Run(k, s, groups.index((s.split, s.workers)), dims, classes) for k, s in enumerate(specs)]
    # A run's loss is summed over the copy of its split with the most pieces.
    widest = {split: groups.index((split, max(w for s, w in groups if s == split))) for split, _ in groups}

    def job(work: dict) -> list:
        shared = sc.broadcast(work)
        try:
            return sc.union([kept[g] for g in sorted(work["runs"].keys() | work["score"].keys())]).mapPartitions(lambda blocks: one_pass(shared.value, blocks)).collect()
        finally:
            shared.destroy()

    try:
        while active := [r for r in runs if r.active]:
            ask: dict[int, list] = {}
            score: dict[int, list] = {}
            asked = [r for r in active if r.goes_on]
            for r in asked:
                ask.setdefault(r.group, []).append((r.nth, r.spec, r.model, r.w, training.step_size_at(r.spec, r.round), r.draws()))
            for r in (r for r in active if r.scored):
                score.setdefault(TEST, []).append((r.nth, r.model, r.w, False))
                gradient = not {"grad_sq", "smooth"}.isdisjoint(measures)
                if gradient or "loss" in measures or r.spec.scheme == "adaptive_period":
                    score.setdefault(widest[r.spec.split], []).append((r.nth, r.model, r.w, gradient))
            found: dict[int, list] = {}
            got: dict = {}
            for chained, nth, *rest in job({"sizes": sizes, "runs": ask, "score": score}) if ask or score else []:
                if chained:
                    found.setdefault(nth, []).append(rest)
                else:
                    held, n, s = rest
                    n0, s0 = got.get((nth, held), (0, 0.0))
                    got[nth, held] = n0 + n, s0 + s
            for r in active:
                m: dict = {}
                if (r.nth, True) in got:
                    n, s = got[r.nth, True]
                    m["accuracy"] = float(s[0]) / n
                if (r.nth, False) in got:
                    n, s = got[r.nth, False]
                    m |= {"loss": float(s[0]) / n} | ({"grad": s[1:] / n} if len(s) > 1 else {})
                if r.trained is not None:
                    r.record(m)
            for r in (r for r in asked if not r.done):  # a run that has just ended needs no further round
                r.step(found.get(r.nth, []))
    finally:
        for rdd in kept.values():
            rdd.unpersist()
    return [row for r in runs for row in r.log]
