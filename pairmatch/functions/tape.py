"""A small reverse-mode tape over NumPy arrays, enough for the models of this library."""

from __future__ import annotations

import numpy as np


class Var:
    """An array, its gradient, and how to pass the gradient on."""

    __slots__ = ("grad", "parents", "push", "v")

    def __init__(self, v, parents=(), push=None):
        self.v, self.parents, self.push, self.grad = np.asarray(v), parents, push, None

    def add_grad(self, g):
        self.grad = g if self.grad is None else self.grad + g

    def backward(self):
        order, seen = [], set()

        def visit(x):
            stack = [(x, iter(x.parents))]
            seen.add(id(x))
            while stack:
                node, rest = stack[-1]
                nxt = next((p for p in rest if id(p) not in seen), None)
                if nxt is None:
                    order.append(node)
                    stack.pop()
                else:
                    seen.add(id(nxt))
                    stack.append((nxt, iter(nxt.parents)))

        visit(self)
        self.grad = np.ones_like(self.v)
        for node in reversed(order):
            if node.push is not None and node.grad is not None:
                node.push(node.grad)

    def __add__(self, o):
        o = var(o)
        return Var(self.v + o.v, (self, o), lambda g: (self.add_grad(_fit(g, self.v)), o.add_grad(_fit(g, o.v))))

    def __sub__(self, o):
        return self + var(o) * -1.0

    def __mul__(self, o):
        o = var(o)
        return Var(self.v * o.v, (self, o), lambda g: (self.add_grad(_fit(g * o.v, self.v)), o.add_grad(_fit(g * self.v, o.v))))

    def __matmul__(self, o):
        def push(g):
            self.add_grad(_fit(g @ np.swapaxes(o.v, -1, -2), self.v))
            o.add_grad(_fit(np.swapaxes(self.v, -1, -2) @ g, o.v))

        return Var(self.v @ o.v, (self, o), push)


def var(x) -> Var:
    return x if isinstance(x, Var) else Var(np.asarray(x, float))


def _fit(g, like):
    """Sum a gradient over broadcast axes."""
    while g.ndim > like.ndim:
        g = g.sum(0)
    for i, n in enumerate(like.shape):
        if n == 1 and g.shape[i] != 1:
            g = g.sum(i, keepdims=True)
    return g


def tanh(x):
    t = np.tanh(x.v)
    return Var(t, (x,), lambda g: x.add_grad(g * (1 - t * t)))


def sigmoid(x):
    s = 1 / (1 + np.exp(-np.clip(x.v, -40, 40)))
    return Var(s, (x,), lambda g: x.add_grad(g * s * (1 - s)))


def relu(x):
    return Var(np.maximum(x.v, 0), (x,), lambda g: x.add_grad(g * (x.v > 0)))


def absolute(x):
    return Var(np.abs(x.v), (x,), lambda g: x.add_grad(g * np.sign(x.v)))


def softmax(x):
    e = np.exp(x.v - x.v.max(-1, keepdims=True))
    s = e / e.sum(-1, keepdims=True)
    return Var(s, (x,), lambda g: x.add_grad(s * (g - (g * s).sum(-1, keepdims=True))))


def log(x):
    c = np.maximum(x.v, 1e-12)
    return Var(np.log(c), (x,), lambda g: x.add_grad(g / c))


def gather(table, ids):
    def push(g):
        out = np.zeros_like(table.v)
        np.add.at(out, ids, g)
        table.add_grad(out)

    return Var(table.v[ids], (table,), push)


def pick(x, index):
    """x[index] for any NumPy index."""
    plain = all(isinstance(i, (int, slice)) for i in (index if isinstance(index, tuple) else (index,)))

    def push(g):
        out = np.zeros_like(x.v)
        if plain:  # no place comes twice
            out[index] = g
        else:
            np.add.at(out, index, g)
        x.add_grad(out)

    return Var(x.v[index], (x,), push)


def total(x, axis=None, keepdims=False):
    def push(g):
        if axis is not None and not keepdims:
            g = np.expand_dims(g, axis)
        x.add_grad(np.broadcast_to(g, x.v.shape).copy())

    return Var(x.v.sum(axis=axis, keepdims=keepdims), (x,), push)


def mean(x, axis=None, keepdims=False):
    n = x.v.size if axis is None else x.v.shape[axis]
    return total(x, axis, keepdims) * (1.0 / n)


def concat(xs, axis=-1):
    def push(g):
        at = 0
        for x in xs:
            n = x.v.shape[axis]
            x.add_grad(np.take(g, range(at, at + n), axis))
            at += n

    return Var(np.concatenate([x.v for x in xs], axis), tuple(xs), push)


def swap(x, a=-1, b=-2):
    return Var(np.swapaxes(x.v, a, b), (x,), lambda g: x.add_grad(np.swapaxes(g, a, b)))


def put_rows(table, places, new):
    """table with the rows at distinct places replaced."""
    out = table.v.copy()
    out[places] = new.v

    def push(g):
        new.add_grad(g[places])
        kept = g.copy()
        kept[places] = 0
        table.add_grad(kept)

    return Var(out, (table, new), push)


def attend(x, q, shut):
    """Mean of the rows of each x[n] by softmax(x[n] @ q[n] + shut[n]): attention of one place a text."""
    s = (x.v @ q.v[:, :, None])[:, :, 0] + shut
    e = np.exp(s - s.max(1, keepdims=True))
    a = e / e.sum(1, keepdims=True)

    def push(g):
        along = (x.v @ g[:, :, None])[:, :, 0]
        ds = a * (along - (a * along).sum(1, keepdims=True))
        q.add_grad((ds[:, None, :] @ x.v)[:, 0])
        x.add_grad(a[:, :, None] * g[:, None, :] + ds[:, :, None] * q.v[:, None, :])

    return Var((a[:, None, :] @ x.v)[:, 0], (x, q), push)


def lstm(x, wx, wh, back=False):
    """States of a gated cell along the rows of x, last row first if back: one node in place of some twenty a row."""
    n, h = len(x.v), len(wh.v)
    order = range(n - 1, -1, -1) if back else range(n)
    zx, out, was, seen = x.v @ wx.v, np.empty((n, h)), np.zeros((n, h)), {}
    c, s = np.zeros(h), np.zeros(h)
    for i in order:
        z, was[i] = zx[i] + s @ wh.v, s
        g, t = 1 / (1 + np.exp(-np.clip(z, -40, 40))), np.tanh(z[2 * h : 3 * h])
        last, c = c, g[:h] * c + g[h : 2 * h] * t
        tc = np.tanh(c)
        out[i] = s = g[3 * h :] * tc
        seen[i] = last, g, t, tc

    def push(grad):
        dz, dc, ds = np.empty((n, 4 * h)), np.zeros(h), np.zeros(h)
        for i in reversed(order):
            last, g, t, tc = seen[i]
            ds, g3 = grad[i] + ds, g[3 * h :]
            dc = dc + ds * g3 * (1 - tc * tc)
            dz[i, :h], dz[i, h : 2 * h], dz[i, 2 * h : 3 * h], dz[i, 3 * h :] = dc * last, dc * t, dc * g[h : 2 * h] * (1 - t * t), ds * tc
            for j in (0, 1, 3):
                dz[i, j * h : (j + 1) * h] *= g[j * h : (j + 1) * h] * (1 - g[j * h : (j + 1) * h])
            dc, ds = dc * g[:h], wh.v @ dz[i]
        x.add_grad(dz @ wx.v.T)
        wx.add_grad(x.v.T @ dz)
        wh.add_grad(was.T @ dz)

    return Var(out, (x, wx, wh), push)


def placed(table, pos, same, ids, twin, mask=None):
    """table[ids] + pos by place + twin * same, times mask: one array, filled in place."""
    n = ids.shape[1]
    out = table.v[ids]
    out += pos.v[:n]
    out += twin[:, :, None] * same.v
    if mask is not None:
        out *= mask

    def push(g):
        g = g if mask is None else g * mask
        rows, places = np.zeros_like(table.v), np.zeros_like(pos.v)
        np.add.at(rows, ids, g)
        places[:n] = g.sum(0)
        table.add_grad(rows)
        pos.add_grad(places)
        same.add_grad(np.tensordot(twin.astype(float), g, 2)[None])

    return Var(out, (table, pos, same), push)


def gru(x, live, wx, wh):
    """Last state of a gated recurrent unit over the places of each x[n]; a place that is not live changes nothing."""
    n, steps, d = x.v.shape[0], x.v.shape[1], len(wh.v)
    zx, h, seen = x.v @ wx.v, np.zeros((n, d)), []
    for t in range(steps):
        zh, a = h @ wh.v, zx[:, t]
        ru = 1 / (1 + np.exp(-np.clip(a[:, : 2 * d] + zh[:, : 2 * d], -40, 40)))
        r, u, on = ru[:, :d], ru[:, d:] * live[:, t, None], live[:, t, None]
        new = np.tanh(a[:, 2 * d :] + r * zh[:, 2 * d :])
        seen.append((h, r, ru[:, d:], on, new, zh[:, 2 * d :]))
        h = h + (new - h) * u

    def push(g):
        dzx, dwh = np.empty_like(zx), np.zeros_like(wh.v)
        for t in range(steps - 1, -1, -1):
            h0, r, u, on, new, zn = seen[t]
            dn = g * u * on * (1 - new * new)
            dr, du = dn * zn * r * (1 - r), g * (new - h0) * on * u * (1 - u)
            dzx[:, t] = np.concatenate([dr, du, dn], 1)
            dzh = np.concatenate([dr, du, dn * r], 1)
            dwh += h0.T @ dzh
            g = g * (1 - u * on) + dzh @ wh.v.T
        x.add_grad(dzx @ wx.v.T)
        wx.add_grad(np.tensordot(x.v, dzx, ((0, 1), (0, 1))))
        wh.add_grad(dwh)

    return Var(h, (x, wx, wh), push)


def reverse_gradient(x, scale=1.0):
    """Identity whose gradient comes back negated."""
    return Var(x.v, (x,), lambda g: x.add_grad(-scale * g))


class AdamW:
    def __init__(self, params: dict[str, Var], lr=2e-3, decay=0.01, b1=0.9, b2=0.999):
        self.p, self.lr, self.decay, self.b1, self.b2, self.t = params, lr, decay, b1, b2, 0
        self.m = {k: np.zeros_like(x.v) for k, x in params.items()}
        self.s = {k: np.zeros_like(x.v) for k, x in params.items()}

    def step(self):
        self.t += 1
        for k, x in self.p.items():
            if x.grad is None:
                continue
            m, v = self.m[k], self.s[k]
            m *= self.b1
            m += (1 - self.b1) * x.grad
            v *= self.b2
            v += (1 - self.b2) * np.square(x.grad)
            under = np.sqrt(v / (1 - self.b2**self.t))
            under += 1e-8
            up = m / (1 - self.b1**self.t)
            up /= under
            up += self.decay * x.v
            up *= self.lr
            x.v = x.v - up
            x.grad = None
