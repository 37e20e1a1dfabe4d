"""Models as numpy kernels over a flat weight vector: init, loss_grad, predict. They run inside Arrow tasks only."""

from __future__ import annotations

from dataclasses import dataclass


def _softmax_loss(z, y):
    """(mean loss, gradient with respect to the scores)."""
    import numpy as np

    z = z - z.max(axis=1, keepdims=True)
    e = np.exp(z)
    p = e / e.sum(axis=1, keepdims=True)
    n = np.arange(len(y))
    loss = float(-np.log(np.maximum(p[n, y], 1e-300)).mean())
    p[n, y] -= 1
    return loss, p / len(y)


@dataclass(frozen=True)
class Model:
    """kind: least_squares, logistic, softmax, mlp, small_cnn. ``dims`` counts the inputs, a bias entry included."""

    kind: str
    dims: int
    classes: int = 2
    hidden: int = 16

    @property
    def size(self) -> int:
        d, c, h = self.dims, self.classes, self.hidden
        return {"least_squares": d, "logistic": d, "softmax": d * c, "mlp": d * h + (h + 1) * c, "small_cnn": 9 * 8 + 8 + 72 * 16 + 16 + (16 * 16 + 1) * c}[self.kind]

    def init(self, seed: int = 0):
        import numpy as np

        if self.kind in ("least_squares", "logistic", "softmax"):
            return np.zeros(self.size)
        rng = np.random.Generator(np.random.PCG64(seed + 1000))
        if self.kind == "mlp":
            a = rng.standard_normal(self.dims * self.hidden) / np.sqrt(self.dims)
            b = rng.standard_normal((self.hidden + 1) * self.classes) / np.sqrt(self.hidden)
            return np.concatenate([a, b])
        parts = [rng.standard_normal(72) / 3, np.zeros(8), rng.standard_normal(1152) * np.sqrt(2 / 72), np.zeros(16), rng.standard_normal(256 * self.classes) / 16, np.zeros(self.classes)]
        return np.concatenate(parts)

    def scores(self, w, x):
        """Raw outputs and what the backward pass needs."""
        import numpy as np

        if self.kind in ("least_squares", "logistic"):
            return x @ w, None
        if self.kind == "softmax":
            return x @ w.reshape(self.dims, self.classes), None
        if self.kind == "mlp":
            cut = self.dims * self.hidden
            a = np.tanh(x @ w[:cut].reshape(self.dims, self.hidden))
            a1 = np.concatenate([a, np.ones((len(a), 1))], axis=1)
            return a1 @ w[cut:].reshape(self.hidden + 1, self.classes), a1
        return self._cnn(w, x)

    def _cnn_parts(self, w):
        ends, at, out = [72, 8, 1152, 16, 256 * self.classes, self.classes], 0, []
        for n in ends:
            out.append(w[at : at + n])
            at += n
        return out[0].reshape(9, 8), out[1], out[2].reshape(72, 16), out[3], out[4].reshape(256, self.classes), out[5]

    @staticmethod
    def _patches(img):
        """3 x 3 neighbourhoods with zero borders: (n, h, w, 9 c)."""
        import numpy as np

        n, h, w, c = img.shape
        padded = np.zeros((n, h + 2, w + 2, c))
        padded[:, 1:-1, 1:-1] = img
        return np.concatenate([padded[:, i : i + h, j : j + w] for i in range(3) for j in range(3)], axis=3)

    def _cnn(self, w, x):
        """8 x 8 grid, 3 x 3 convolution to 8 maps, rectifier, 2 x 2 maximum, 3 x 3 convolution to 16 maps, rectifier, dense."""
        import numpy as np

        k1, b1, k2, b2, k3, b3 = self._cnn_parts(w)
        p1 = self._patches(x[:, :64].reshape(-1, 8, 8, 1))
        z1 = p1 @ k1 + b1
        a1 = np.maximum(z1, 0)
        cells = a1.reshape(-1, 4, 2, 4, 2, 8).transpose(0, 1, 3, 5, 2, 4).reshape(-1, 4, 4, 8, 4)
        pick = cells.argmax(axis=4)
        pooled = np.take_along_axis(cells, pick[..., None], axis=4)[..., 0]
        p2 = self._patches(pooled)
        z2 = p2 @ k2 + b2
        a2 = np.maximum(z2, 0).reshape(len(x), 256)
        return a2 @ k3 + b3, (p1, z1, pick, p2, z2, a2, k2, k3)

    def loss_grad(self, w, x, y):
        """(mean loss, mean gradient) over a batch."""
        import numpy as np

        z, kept = self.scores(w, x)
        if self.kind == "least_squares":
            r = z - y
            return float((r * r).mean() / 2), x.T @ r / len(y)
        if self.kind == "logistic":
            p = 1 / (1 + np.exp(-z))
            return float(np.logaddexp(0, np.where(y > 0, -z, z)).mean()), x.T @ (p - (y > 0)) / len(y)
        y = y.astype(np.int64)
        loss, dz = _softmax_loss(z, y)
        if self.kind == "softmax":
            return loss, (x.T @ dz).ravel()
        if self.kind == "mlp":
            cut = self.dims * self.hidden
            top = w[cut:].reshape(self.hidden + 1, self.classes)
            da = (dz @ top.T)[:, :-1] * (1 - kept[:, :-1] ** 2)
            return loss, np.concatenate([(x.T @ da).ravel(), (kept.T @ dz).ravel()])
        return loss, self._cnn_back(dz, kept)

    def _cnn_forward(self, w, x):
        """The network's scores alone, with each convolution as one dense matrix: a few large products, and no patches are kept."""
        import numpy as np

        k1, b1, k2, b2, k3, b3 = self._cnn_parts(w)
        first, second = np.zeros((8, 8, 8, 8, 8)), np.zeros((4, 4, 8, 4, 4, 16))
        for q in range(9):
            i, j = q // 3 - 1, q % 3 - 1
            for r, c in ((r, c) for r in range(8) for c in range(8) if 0 <= r + i < 8 and 0 <= c + j < 8):
                first[r + i, c + j, r, c] = k1[q]
            for r, c in ((r, c) for r in range(4) for c in range(4) if 0 <= r + i < 4 and 0 <= c + j < 4):
                second[r + i, c + j, :, r, c] = k2[q * 8 : q * 8 + 8]
        # Columns by place inside a pooling cell, then by cell and map.
        first = first.reshape(64, 4, 2, 4, 2, 8).transpose(0, 2, 4, 1, 3, 5).reshape(64, 4, 128)
        pooled = x[:, :64] @ first[:, 0]
        for k in range(1, 4):
            np.maximum(pooled, x[:, :64] @ first[:, k], out=pooled)
        pooled += np.tile(b1, 16)
        a2 = np.maximum(pooled, 0, out=pooled) @ second.reshape(128, 256)
        a2 += np.tile(b2, 16)
        return np.maximum(a2, 0, out=a2) @ k3 + b3

    def _outputs(self, w, x):
        return self._cnn_forward(w, x) if self.kind == "small_cnn" else self.scores(w, x)[0]

    def loss(self, w, x, y) -> float:
        """The mean loss alone, without a backward pass."""
        import numpy as np

        z = self._outputs(w, x)
        if self.kind == "least_squares":
            return float(((z - y) ** 2).mean() / 2)
        if self.kind == "logistic":
            return float(np.logaddexp(0, np.where(y > 0, -z, z)).mean())
        return _softmax_loss(z, y.astype(np.int64))[0]

    def _cnn_back(self, dz, kept):
        import numpy as np

        p1, z1, pick, p2, z2, a2, k2, k3 = kept
        n = len(dz)
        dz2 = (dz @ k3.T).reshape(n, 4, 4, 16) * (z2 > 0)
        dp2 = dz2 @ k2.T
        padded = np.zeros((n, 6, 6, 8))
        for q in range(9):
            i, j = divmod(q, 3)
            padded[:, i : i + 4, j : j + 4] += dp2[..., q * 8 : q * 8 + 8]
        dpool = padded[:, 1:-1, 1:-1]
        cells = np.zeros((n, 4, 4, 8, 4))
        np.put_along_axis(cells, pick[..., None], dpool[..., None], axis=4)
        da1 = cells.reshape(n, 4, 4, 8, 2, 2).transpose(0, 1, 4, 2, 5, 3).reshape(n, 8, 8, 8)
        dz1 = da1 * (z1 > 0)
        parts = [p1.reshape(-1, 9).T @ dz1.reshape(-1, 8), dz1.sum(axis=(0, 1, 2)), p2.reshape(-1, 72).T @ dz2.reshape(-1, 16), dz2.sum(axis=(0, 1, 2)), a2.T @ dz, dz.sum(axis=0)]
        return np.concatenate([g.ravel() for g in parts])

    def sample_grad_sq(self, w, x, y):
        """Squared length of each sample's own gradient. A dense layer's is the product of its input's and its error's."""
        import numpy as np

        if self.kind == "small_cnn":  # shared weights: one backward pass for each sample
            return np.array([(g * g).sum() for g in (self.loss_grad(w, x[k : k + 1], y[k : k + 1])[1] for k in range(len(y)))])
        z, kept = self.scores(w, x)
        square = lambda a: (a * a).sum(axis=1)
        if self.kind == "least_squares":
            return square(x) * (z - y) ** 2
        if self.kind == "logistic":
            return square(x) * (1 / (1 + np.exp(-z)) - (y > 0)) ** 2
        dz = _softmax_loss(z, y.astype(np.int64))[1] * len(y)
        if self.kind == "softmax":
            return square(x) * square(dz)
        top = w[self.dims * self.hidden :].reshape(self.hidden + 1, self.classes)
        da = (dz @ top.T)[:, :-1] * (1 - kept[:, :-1] ** 2)
        return square(x) * square(da) + square(kept) * square(dz)

    def predict(self, w, x):
        z = self._outputs(w, x)
        if self.kind == "least_squares":
            return z
        return (z > 0).astype(int) if self.kind == "logistic" else z.argmax(axis=1)

    def evaluate(self, w, x, y):
        """(mean loss, share correct); the share is 0 for least squares."""
        loss, _ = self.loss_grad(w, x, y)
        return loss, 0.0 if self.kind == "least_squares" else float((self.predict(w, x) == y).mean())


def least_squares(dims: int) -> Model:
    return Model("least_squares", dims)


def logistic(dims: int) -> Model:
    return Model("logistic", dims)


def softmax(dims: int, classes: int) -> Model:
    return Model("softmax", dims, classes)


def mlp(dims: int, hidden: int, classes: int) -> Model:
    return Model("mlp", dims, classes, hidden)


def small_cnn(classes: int) -> Model:
    return Model("small_cnn", 65, classes)


def local_chain(model: Model, w, batches, step_size: float):
    """A worker's sequence of mini-batch steps from the round's model."""
    for x, y in batches:
        w = w - step_size * model.loss_grad(w, x, y)[1]
    return w


def softmax_chains(ws, xs, ys, begins, steps, step_sizes, dims: int, classes: int):
    """Chains of several runs with the softmax model, a step of all of them at a time. ``xs`` and ``ys`` hold mini-batches of one size;
    a run's own are ``steps`` ones from ``begins``."""
    import numpy as np

    order = np.argsort([-n for n in steps], kind="stable")
    w = np.stack([ws[k].reshape(dims, classes).T for k in order])
    begins, steps, rates = np.asarray(begins)[order], np.asarray(steps)[order], np.asarray(step_sizes, float)[order, None, None]
    size = xs.shape[1]
    for s in range(steps[0]):
        n = int((steps > s).sum())
        x, y = xs[begins[:n] + s], ys[begins[:n] + s].astype(np.int64)
        z = w[:n] @ x.transpose(0, 2, 1)
        z -= z.max(axis=1, keepdims=True)
        np.exp(z, out=z)
        z /= z.sum(axis=1, keepdims=True)
        z[np.arange(n)[:, None], y, np.arange(size)] -= 1
        z /= size
        w[:n] -= rates[:n] * (z @ x)
    out: list = [None] * len(ws)
    for k, own in zip(order, w, strict=True):
        out[k] = own.T.ravel()
    return out


def softmax_scores(wide, x, y: int, classes: int, loss: bool):
    """Of many softmax models (``wide``: inputs x (classes x models)) on rows of one label: correct rows, or the summed loss."""
    import numpy as np

    z = (x @ wide).reshape(len(x), classes, -1)
    if not loss:
        if not 0 <= y < classes:
            return np.zeros(z.shape[2])
        own, right = z[:, y], np.ones((len(x), z.shape[2]), bool)
        for k in range(classes):  # the first of equal scores is the prediction
            if k != y:
                right &= own > z[:, k] if k < y else own >= z[:, k]
        return right.sum(axis=0).astype(float)
    z -= z.max(axis=1, keepdims=True)
    own = z[:, y].copy()
    return np.minimum(np.log(np.exp(z, out=z).sum(axis=1)) - own, -np.log(1e-300)).sum(axis=0)


def gradients_at(model: Model, w, batches):
    """Mean gradient of several batches, all at the same model."""
    import numpy as np

    return np.mean([model.loss_grad(w, x, y)[1] for x, y in batches], axis=0)


def average(w, locals_, weights, steps, rule: str = "uniform"):
    """The next model from local ones. ``uniform`` and ``inverse_model`` average models by weight;
    ``normalised_direction`` averages progress for each step and takes the mean number of steps along it."""
    import numpy as np

    locals_, weights, steps = np.asarray(locals_), np.asarray(weights, float), np.asarray(steps, float)
    if not len(locals_):
        return w
    if rule == "normalised_direction":
        return w - steps.mean() * ((w - locals_) / steps[:, None]).mean(axis=0)
    if rule == "inverse_model":
        weights = 1 / steps
    elif rule == "uniform":
        weights = np.ones(len(steps))
    elif rule != "weighted":
        raise ValueError(f"unknown rule {rule!r}")
    return (locals_ * weights[:, None]).sum(axis=0) / weights.sum()
