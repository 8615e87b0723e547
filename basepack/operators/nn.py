"""Numeric kernels of the learned coders: one small reverse-mode core, layers, and the three models.

Every function takes arrays or Tensors; with arrays nothing is recorded, so coding and training run the same code.
"""

from __future__ import annotations

import numpy as np


class Tensor:
    """An array that remembers how to send its gradient back."""

    __array_ufunc__ = None  # arrays on the left leave the operation to this class

    def __init__(self, data, parents=(), back=None) -> None:
        self.data, self.parents, self.back, self.grad = np.asarray(data, float), parents, back, None

    @property
    def shape(self):
        return self.data.shape

    def backward(self) -> None:
        order, seen = [], set()

        def visit(t):
            if id(t) not in seen:
                seen.add(id(t))
                for p in t.parents:
                    visit(p)
                order.append(t)

        visit(self)
        self.grad = np.ones_like(self.data)
        for t in reversed(order):
            if t.back is not None and t.grad is not None:
                for p, g in zip(t.parents, t.back(t.grad), strict=True):
                    if g is not None:
                        p.grad = g if p.grad is None else p.grad + g

    def __add__(self, o):
        return apply(lambda a, b: a + b, lambda g, a, b, y: (fit(g, a), fit(g, b)), self, o)

    __radd__ = __add__

    def __mul__(self, o):
        return apply(lambda a, b: a * b, lambda g, a, b, y: (fit(g * b, a), fit(g * a, b)), self, o)

    __rmul__ = __mul__

    def __sub__(self, o):
        return self + o * -1.0

    def __matmul__(self, o):
        return matmul(self, o)

    def __rmatmul__(self, o):
        return matmul(o, self)


def data(x):
    return x.data if isinstance(x, Tensor) else x


def apply(fn, back, *xs):
    arrays = [np.asarray(data(x)) for x in xs]
    y = fn(*arrays)
    if not any(isinstance(x, Tensor) for x in xs):
        return y
    parents = [x if isinstance(x, Tensor) else Tensor(x) for x in xs]
    return Tensor(y, parents, lambda g: back(g, *arrays, y))


def fit(g, like):
    """Sum a gradient over the axes along which `like` was repeated."""
    while g.ndim > like.ndim:
        g = g.sum(axis=0)
    for i, n in enumerate(like.shape):
        if n == 1 and g.shape[i] != 1:
            g = g.sum(axis=i, keepdims=True)
    return g


def matmul(a, b):
    t = lambda x: np.swapaxes(x, -1, -2)

    def fn(a, b):  # rows of all windows times one matrix are one product
        return (a.reshape(-1, a.shape[-1]) @ b).reshape(*a.shape[:-1], b.shape[-1]) if a.ndim == 3 and b.ndim == 2 else a @ b

    def back(g, a, b, y):
        if a.ndim == 3 and b.ndim == 2:
            rows = g.reshape(-1, g.shape[-1])
            return (rows @ b.T).reshape(a.shape), a.reshape(-1, a.shape[-1]).T @ rows
        return fit(g @ t(b), a), fit(t(a) @ g, b)

    return apply(fn, back, a, b)


def relu(x):
    return apply(lambda a: np.maximum(a, 0), lambda g, a, y: (g * (a > 0),), x)


def tanh(x):
    return apply(np.tanh, lambda g, a, y: (g * (1 - y * y),), x)


def sigmoid(x):
    return apply(lambda a: 1 / (1 + np.exp(-np.clip(a, -40, 40))), lambda g, a, y: (g * y * (1 - y),), x)


def gelu(x):
    """The tanh form."""
    c = np.sqrt(2 / np.pi)

    def fn(a):
        return 0.5 * a * (1 + np.tanh(c * (a + 0.044715 * (a * a * a))))

    def back(g, a, y):
        t = np.tanh(c * (a + 0.044715 * (a * a * a)))
        return (g * (0.5 * (1 + t) + 0.5 * a * (1 - t * t) * c * (1 + 3 * 0.044715 * a * a)),)

    return apply(fn, back, x)


def softmax(x):
    def fn(a):
        e = np.exp(a - a.max(axis=-1, keepdims=True))
        return e / e.sum(axis=-1, keepdims=True)

    return apply(fn, lambda g, a, y: (y * (g - (g * y).sum(axis=-1, keepdims=True)),), x)


def layer_norm(x, gain, shift, eps=1e-5):
    def fn(a):
        return (a - a.mean(axis=-1, keepdims=True)) / np.sqrt(a.var(axis=-1, keepdims=True) + eps)

    def back(g, a, y):
        sd = np.sqrt(a.var(axis=-1, keepdims=True) + eps)
        return ((g - g.mean(axis=-1, keepdims=True) - y * (g * y).mean(axis=-1, keepdims=True)) / sd,)

    return apply(fn, back, x) * gain + shift


def batch_norm(x, gain, shift, running, train: bool, momentum=0.1, eps=1e-5):
    """Channels last. Running statistics are frozen when coding and updated, without gradient, when training."""
    if train:
        a = data(x)
        mean, var = a.mean(axis=(0, 1)), a.var(axis=(0, 1))
        running["mean"] = (1 - momentum) * running["mean"] + momentum * mean
        running["var"] = (1 - momentum) * running["var"] + momentum * var
    return (x - running["mean"]) * (1 / np.sqrt(running["var"] + eps)) * gain + shift


def max_pool(x, size):
    """(batch, length, d): non-overlapping maxima, a remainder is left out."""
    def fn(a):
        n = a.shape[1] // size
        return a[:, : n * size].reshape(a.shape[0], n, size, a.shape[2]).max(axis=2)

    def back(g, a, y):
        n = a.shape[1] // size
        blocks = a[:, : n * size].reshape(a.shape[0], n, size, a.shape[2])
        first = blocks.argmax(axis=2)
        out = np.zeros_like(blocks)
        np.put_along_axis(out, first[:, :, None, :], g[:, :, None, :], axis=2)
        whole = np.zeros_like(a)
        whole[:, : n * size] = out.reshape(a.shape[0], n * size, a.shape[2])
        return (whole,)

    return apply(fn, back, x)


def conv1d(x, w, b):
    """(batch, length, e) with kernel (k, e, d): valid, stride 1, as one product."""
    k, learned = data(w).shape[0], isinstance(x, Tensor)

    def cols(a):
        n = a.shape[1] - k + 1
        v = np.lib.stride_tricks.sliding_window_view(a, k, axis=1)  # batch, n, e, k
        return v.transpose(0, 1, 3, 2).reshape(a.shape[0], n, k * a.shape[2])

    def fn(a, w, b):
        return cols(a) @ w.reshape(-1, w.shape[2]) + b

    def back(g, a, w, b, y):
        rows = g.reshape(-1, g.shape[2])
        gw = (cols(a).reshape(len(rows), -1).T @ rows).reshape(w.shape)
        if not learned:
            return None, gw, rows.sum(axis=0)
        gc = (rows @ w.reshape(-1, w.shape[2]).T).reshape(g.shape[0], g.shape[1], k, a.shape[2])
        ga = np.zeros_like(a)
        for i in range(k):
            ga[:, i : i + g.shape[1]] += gc[:, :, i]
        return ga, gw, rows.sum(axis=0)

    return apply(fn, back, x, w, b)


def take(table, index):
    def back(g, t, y):
        out = np.zeros_like(t)
        np.add.at(out, index, g)
        return (out,)

    return apply(lambda t: t[index], back, table)


def concat(xs, axis):
    cuts = np.cumsum([data(x).shape[axis] for x in xs])[:-1]
    return apply(lambda *a: np.concatenate(a, axis=axis), lambda g, *a: tuple(np.split(g, cuts, axis=axis)), *xs)


def pick(x, index):
    def back(g, a, y):
        out = np.zeros_like(a)
        out[index] = g
        return (out,)

    return apply(lambda a: a[index], back, x)


def reshape(x, *shape):
    return apply(lambda a: a.reshape(*shape), lambda g, a, y: (g.reshape(a.shape),), x)


def swap(x):
    return apply(lambda a: np.swapaxes(a, -1, -2), lambda g, a, y: (np.swapaxes(g, -1, -2),), x)


def dropout(x, rate, rng):
    if rng is None or rate == 0:
        return x
    return x * ((rng.random(data(x).shape) >= rate) / (1 - rate))


def snap(x, bits=8):
    """To a grid of small binary fractions: sums and products of such numbers are exact in doubles in any order."""
    return np.rint(x * (1 << bits)) / (1 << bits) if not isinstance(x, Tensor) else x


def sinusoid(positions, d, freq_base=10000.0):
    j = np.arange(d)
    angle = np.asarray(positions)[:, None] / freq_base ** ((j // 2 * 2) / d)
    return np.where(j % 2 == 0, np.sin(angle), np.cos(angle))


def init(cfg, seed: int = 42) -> dict[str, np.ndarray]:
    """Seeded weights of a model."""
    rng = np.random.default_rng(seed)
    d, e, words = cfg.d_model, cfg.width, 4**cfg.ngram

    def lin(*shape):
        return rng.normal(0, 1 / np.sqrt(np.prod(shape[:-1])), shape)

    w = {"conv_w": lin(cfg.kernel, e * cfg.byte_group, d), "conv_b": np.zeros(d)}
    if cfg.input_coding == "embedding" or cfg.ngram > 1 or cfg.byte_group > 1:
        w["embed"] = rng.normal(0, 1, (words, e))
    if cfg.kind == "carry":
        w |= {"bn_g": np.ones(d), "bn_b": np.zeros(d), "q": lin(d, d), "k": lin(d, d), "v": lin(d, d), "u_bias": np.zeros(d), "v_bias": np.zeros(d)}
        w |= {"ln1_g": np.ones(d), "ln1_b": np.zeros(d), "ln2_g": np.ones(d), "ln2_b": np.zeros(d)}
        w |= {"f1": lin(d, cfg.ffn), "f1_b": np.zeros(cfg.ffn), "f2": lin(cfg.ffn, d), "f2_b": np.zeros(d), "head": lin(d, cfg.alphabet), "head_b": np.zeros(cfg.alphabet)}
    else:
        h = cfg.hidden
        for side in ("f", "b")[: 2 if cfg.kind == "bilstm" else 1]:
            w |= {f"x_{side}": lin(d, 4 * h), f"h_{side}": lin(h, 4 * h), f"g_{side}": np.zeros(4 * h)}
        wide = h * (2 if cfg.kind == "bilstm" else 1)
        if cfg.kind == "bilstm":
            w["score"] = lin(wide, 1)
        w |= {"head": lin(wide, cfg.alphabet), "head_b": np.zeros(cfg.alphabet)}
    return w


def running(cfg) -> dict:
    return {"mean": np.zeros(cfg.d_model), "var": np.ones(cfg.d_model)}


def inputs(codes, w, cfg):
    """(batch, context) codes to (batch, length, width): words, embeddings, byte groups."""
    words = codes
    if cfg.ngram > 1:
        b = codes.reshape(codes.shape[0], -1, cfg.ngram)
        words = (b * 4 ** np.arange(cfg.ngram - 1, -1, -1)).sum(axis=-1)
    x = take(w["embed"], words) if "embed" in w else np.eye(4**cfg.ngram)[words]
    if cfg.byte_group > 1:
        x = reshape(x, codes.shape[0], -1, cfg.width * cfg.byte_group)
    return x


def features(codes, w, cfg, stats, rng=None):
    x = conv1d(inputs(codes, w, cfg), w["conv_w"], w["conv_b"])
    x = max_pool(relu(x), cfg.pool)
    if cfg.kind == "carry":
        x = batch_norm(x, w["bn_g"], w["bn_b"], stats, rng is not None)
    return dropout(x, cfg.dropout, rng)


def track(codes, w, cfg, stats):
    """(batch, places, d): what `features` of frozen weights gives for a row of any window that begins at a place; windows overlap, so
    each row is computed once and not for every window that holds it."""
    n, step, codes = codes.shape[1], cfg.ngram * cfg.byte_group, codes.astype(np.int64)
    m = n - cfg.ngram + 1
    words = sum(codes[:, i : i + m] * 4 ** (cfg.ngram - 1 - i) for i in range(cfg.ngram))
    x = w["embed"][words] if "embed" in w else np.eye(4**cfg.ngram)[words]
    m -= (cfg.byte_group - 1) * cfg.ngram
    x = np.concatenate([x[:, i * cfg.ngram : i * cfg.ngram + m] for i in range(cfg.byte_group)], axis=2)
    kernel, wide = w["conv_w"].shape[:2]
    m -= (kernel - 1) * step
    a, b, c = x.strides
    cols = np.lib.stride_tricks.as_strided(x, (len(x), m, kernel, wide), (a, b, b * step, c)).reshape(len(x), m, kernel * wide)
    x = np.maximum(cols @ w["conv_w"].reshape(kernel * wide, -1) + w["conv_b"], 0)
    m -= (cfg.pool - 1) * step
    y = x[:, :m]
    for i in range(1, cfg.pool):
        y = np.maximum(y, x[:, i * step : i * step + m])
    return batch_norm(y, w["bn_g"], w["bn_b"], stats, False) if cfg.kind == "carry" else y


def windows_of(tracked, first: int, cfg):
    """The rows of `features` of the window that begins at a place of `track`."""
    step = cfg.ngram * cfg.byte_group * cfg.pool
    return tracked[:, first : first + step * (cfg.rows - 1) + 1 : step]


def every_window(tracked, n: int, cfg):
    """(batch, n, rows, d): windows_of each of the first n places, as a view."""
    step = cfg.ngram * cfg.byte_group * cfg.pool
    a, b, c = tracked.strides
    return np.lib.stride_tricks.as_strided(tracked, (len(tracked), n, cfg.rows, cfg.d_model), (a, b, b * step, c), writeable=False)


def attention(x, memory, w, cfg):
    """Queries from x; keys and values from memory and x; positions as configured; any number of heads."""
    both = concat([memory, x], 1) if memory is not None else x
    n, m, d = data(x).shape[1], data(both).shape[1], cfg.d_model
    offset = np.arange(n)[:, None] + (m - n) - np.arange(m)[None, :]  # i - j, memory stands before
    if cfg.position == "absolute":
        g = sinusoid(np.arange(m), d)
        xq, xk = x + g[m - n :], both + g
    else:
        xq, xk = x, both
    parts, size = [], d // cfg.heads
    values = both @ w["v"]
    for k in range(cfg.heads):
        s = np.s_[k * size : (k + 1) * size]
        wq, wk = pick(w["q"], np.s_[:, s]), pick(w["k"], np.s_[:, s])
        keys = xk @ wk
        if cfg.position == "relative":
            score = ((xq + w["u_bias"]) @ wq) @ swap(keys)
            table = sinusoid(np.arange(-(n - 1), m), d) @ wk
            far = ((xq + w["v_bias"]) @ wq) @ swap(table)
            score = score + pick(far, np.s_[:, np.arange(n)[:, None], offset + n - 1])
        else:
            score = (xq @ wq) @ swap(keys)
        parts.append(softmax(score * (1 / np.sqrt(size))) @ pick(values, np.s_[:, :, s]))
    return concat(parts, 2) if cfg.heads > 1 else parts[0]


def carry_step(codes, state, w, cfg, stats, rng=None, seen=None):
    """One window: probabilities (batch, symbols) before softmax, and the next state. seen: its features, if they are known."""
    grid = snap if cfg.numeric_mode == "grid" else (lambda x: x)
    x = grid(features(codes, w, cfg, stats, rng) if seen is None else seen)
    if cfg.memory == "none":
        memory = None
    else:
        memory = state if state is not None else np.zeros((codes.shape[0], cfg.segments * data(x).shape[1], cfg.d_model))
    a = grid(attention(x, memory, w, cfg))
    h = x + a if cfg.block_order == "standard" else a
    h = dropout(layer_norm(h, w["ln1_g"], w["ln1_b"]), cfg.dropout, rng)
    f = grid(layer_norm(h, w["ln2_g"], w["ln2_b"]))
    if cfg.block_order == "standard":
        out = h + (dropout(gelu(grid(f @ w["f1"] + w["f1_b"])), cfg.dropout, rng) @ w["f2"] + w["f2_b"])
    else:
        out = dropout(gelu((f @ w["f1"] + w["f1_b"]) @ w["f2"] + w["f2_b"]), cfg.dropout, rng)
    out = grid(out)
    logits = grid(pick(out, np.s_[:, -1]) @ w["head"] + w["head_b"])
    keep = data(out if cfg.memory == "latent" else x)  # no gradient through the state
    if cfg.segments > 1 and memory is not None:
        keep = np.concatenate((data(memory), keep), axis=1)[:, -cfg.segments * keep.shape[1] :]
    return logits, keep


def lstm(x, w, side, reverse=False):
    """(batch, places, hidden): the hidden state at every place, one operation with its own way back through the places."""
    flip = np.s_[:, ::-1] if reverse else np.s_[:, :]

    def fn(xs, u, cells=None):
        xs = xs[flip]
        b, n, size = len(xs), xs.shape[1], len(u)
        h, c, out = np.zeros((b, size)), np.zeros((b, size)), np.empty((b, n, size))
        for t in range(n):
            z = xs[:, t] + h @ u
            gate = 1 / (1 + np.exp(-np.clip(z[:, : 3 * size] + ones, -40, 40)))
            i, f, o = gate[:, :size], gate[:, size : 2 * size], gate[:, 2 * size :]
            g, before = np.tanh(z[:, 3 * size :]), c
            c = f * c + i * g
            top = np.tanh(c)
            h = out[:, t] = o * top
            if cells is not None:
                cells.append((i, f, o, g, before, top))
        return out[flip]

    def back(grad, xs, u, y):
        cells: list = []
        out, grad = fn(xs, u, cells)[flip], grad[flip]
        size, n = len(u), xs.shape[1]
        gz, gu = np.empty((len(xs), n, 4 * size)), np.zeros_like(u)
        gh, gc = np.zeros((len(xs), size)), np.zeros((len(xs), size))
        for t in reversed(range(n)):
            i, f, o, g, before, top = cells[t]
            gh = gh + grad[:, t]
            gc = gc + gh * o * (1 - top * top)
            z = gz[:, t]
            z[:, :size], z[:, size : 2 * size] = gc * g * i * (1 - i), gc * before * f * (1 - f)
            z[:, 2 * size : 3 * size], z[:, 3 * size :] = gh * top * o * (1 - o), gc * i * (1 - g * g)
            if t:
                gu += out[:, t - 1].T @ z
            gh, gc = z @ u.T, gc * f
        return gz[flip], gu

    u = w[f"h_{side}"]
    size = len(data(u))
    ones = np.concatenate((np.zeros(size), np.ones(size), np.zeros(size)))  # the forgetting gate begins open
    return apply(fn, back, x @ w[f"x_{side}"] + w[f"g_{side}"], u)


def lstm_step(codes, state, w, cfg, stats, rng=None, seen=None):
    """Windows stand alone here: conv features, then one direction, or both with attention over positions."""
    grid = snap if cfg.numeric_mode == "grid" else (lambda x: x)
    x = grid(features(codes, w, cfg, stats, rng) if seen is None else seen)
    seen = lstm(x, w, "f")
    if cfg.kind == "bilstm":
        both = concat([seen, lstm(x, w, "b", reverse=True)], 2)
        weight = softmax(swap(both @ w["score"]))
        last = reshape(weight @ both, data(x).shape[0], -1)
    else:
        last = pick(seen, np.s_[:, -1])
    return grid(grid(last) @ w["head"] + w["head_b"]), None


def step(codes, state, w, cfg, stats, rng=None, seen=None):
    return (carry_step if cfg.kind == "carry" else lstm_step)(codes, state, w, cfg, stats, rng, seen)


def walker(models: list[dict], cfg, lanes: int):
    """walk(windows): (models, lanes, places, rows, d) features of the next places to logits (models, places, lanes, symbols), as by
    `step` place by place. The state goes on from call to call. What does not need the state is done for all places at once."""
    if cfg.kind != "carry":

        def alone(windows):
            e, b, n = windows.shape[:3]
            found = [step(None, None, w, cfg, None, seen=x.reshape(b * n, *x.shape[2:]))[0] for w, x in zip(models, windows, strict=True)]
            return np.stack(found).reshape(e, b, n, -1).swapaxes(1, 2)

        return alone
    if cfg.heads > 1 or cfg.position == "absolute":
        states = [None] * len(models)

        def one_by_one(windows):
            out = []
            for k, w in enumerate(models):
                found = []
                for t in range(windows.shape[2]):
                    logits, states[k] = step(np.empty((lanes, 0)), states[k], w, cfg, None, seen=windows[k, :, t])
                    found.append(logits)
                out.append(np.stack(found))
            return np.stack(out)

        return one_by_one
    return _carry_walker(models, cfg, lanes)


def _carry_walker(models: list[dict], cfg, lanes: int):
    """walker of one head with relative or no positions. Scores are queries times all of memory and window, both before their
    projection, which is put into the queries; likewise for values."""
    e, n, d = len(models), cfg.rows, cfg.d_model
    kept = 0 if cfg.memory == "none" else cfg.segments * n
    m, scale = kept + n, 1 / np.sqrt(d)
    grid = cfg.numeric_mode == "grid"
    weight = {k: np.stack([w[k] for w in models]) for k in models[0]}
    row = {k: weight[k][:, None] for k in ("f1_b", "f2_b", "ln1_g", "ln1_b", "ln2_g", "ln2_b", "head_b")}
    both = weight["q"] @ swap(weight["k"]) * scale
    offset = np.arange(n)[:, None] + (m - n) - np.arange(m)[None, :] + n - 1
    table = swap(weight["q"] @ swap(sinusoid(np.arange(-(n - 1), m), d) @ weight["k"])) * scale  # models, offsets, d
    seen = np.zeros((e, lanes, m, d))  # memory, then the window

    def snapped(x):
        if grid:
            x *= 256.0
            np.rint(x, out=x)
            x *= 1 / 256
        return x

    def normed(x, gain, shift, eps=1e-5):
        y = x - x.sum(axis=-1, keepdims=True) * (1 / d)
        var = np.einsum("eld,eld->el", y, y)[..., None]
        var *= 1 / d
        var += eps
        y /= np.sqrt(var, out=var)
        y *= gain
        y += shift
        return y

    c = np.sqrt(2 / np.pi)

    def bent(x):
        y = x * x
        y *= x
        y *= 0.044715
        y += x
        y *= c
        np.tanh(y, out=y)
        y += 1
        y *= x
        y *= 0.5
        return y

    def walk(windows):
        places = windows.shape[2]
        x = snapped(np.ascontiguousarray(windows.transpose(2, 0, 1, 3, 4)))  # places, models, lanes, rows, d
        wide = x.reshape(places, e, lanes * n, d)
        if cfg.position == "relative":
            query = ((wide + weight["u_bias"][:, None]) @ both).reshape(x.shape)
            far = ((wide + weight["v_bias"][:, None]) @ swap(table)).reshape(*x.shape[:-1], -1)
            far = np.take_along_axis(far, np.broadcast_to(offset, (*x.shape[:-1], m)), -1)
        else:
            query, far = (wide @ both).reshape(x.shape), None
        ends = np.empty((places, e, lanes, d))
        for t in range(places):
            seen[:, :, kept:] = x[t]
            share = query[t] @ swap(seen)
            if far is not None:
                share += far[t]
            share -= share.max(axis=-1, keepdims=True)
            np.exp(share, out=share)
            share /= share.sum(axis=-1, keepdims=True)
            a = snapped((share @ seen).reshape(e, lanes * n, d) @ weight["v"])
            if cfg.block_order == "standard":
                a += wide[t]
            h = normed(a, row["ln1_g"], row["ln1_b"])
            f = snapped(normed(h, row["ln2_g"], row["ln2_b"])) @ weight["f1"]
            f += row["f1_b"]
            if cfg.block_order == "standard":
                out = bent(snapped(f)) @ weight["f2"]
                out += row["f2_b"]
                out += h
            else:
                out = f @ weight["f2"]
                out += row["f2_b"]
                out = bent(out)
            out = snapped(out).reshape(e, lanes, n, d)
            ends[t] = out[:, :, -1]
            if kept:
                if cfg.segments > 1:
                    seen[:, :, : kept - n] = seen[:, :, n:kept].copy()
                seen[:, :, kept - n : kept] = out if cfg.memory == "latent" else x[t]
        return snapped(ends.swapaxes(0, 1).reshape(e, places * lanes, d) @ weight["head"] + row["head_b"]).reshape(e, places, lanes, -1)

    return walk


def loss(logits, target):
    """Mean cross-entropy in bits."""
    rows = np.arange(len(target))

    def fn(a):
        top = a.max(axis=1, keepdims=True)
        return ((np.log(np.exp(a - top).sum(axis=1)) + top[:, 0] - a[rows, target]) / np.log(2)).mean()

    def back(g, a, y):
        e = np.exp(a - a.max(axis=1, keepdims=True))
        p = e / e.sum(axis=1, keepdims=True)
        p[rows, target] -= 1
        return (g * p / len(target) / np.log(2),)

    return apply(fn, back, logits)
