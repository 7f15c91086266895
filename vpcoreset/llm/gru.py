"""A gated recurrent network with a class-factored output, in numpy.

Words of the vocabulary's head have classes of up to ``IN_CLASS`` words each and a softmax inside their class;
words of the tail have classes without one. A step reads the code of the last word (0: start of a text), the state is
carried from window to window and set to zero where a text starts. Training backpropagates through windows of
``WINDOW`` steps (truncated there) and updates by Adagrad.
"""

from __future__ import annotations

import heapq

import numpy as np

HIDDEN, IN_CLASS, WINDOW, LANES = 16, 64, 16, 256
#: Longest run of a text in training; scoring carries the state through whole texts.
PIECE = 2048
NAMES = ("inputs", "recurrent", "class_w", "class_b", "word_w", "word_b")


def initial(codes: int, class_mass: np.ndarray, word_mass: np.ndarray, seed: int = 5) -> dict[str, np.ndarray]:
    """Output weights are zero and biases are log shares: the untrained network is the unigram model.

    class_mass: mass of each class, head classes first; word_mass: (head classes, IN_CLASS) masses, zero where no word is.
    """
    rng = np.random.default_rng(seed)
    h = HIDDEN
    share = np.maximum(word_mass, 1e-30) / np.maximum(word_mass.sum(1, keepdims=True), 1e-30)
    params = {
        "inputs": rng.standard_normal((codes, 3 * h)) * 0.5,
        "recurrent": rng.standard_normal((h, 3 * h)) * (0.5 / h**0.5),
        "class_w": np.zeros((h, len(class_mass))), "class_b": np.log(np.maximum(class_mass, 1e-2) / max(class_mass.sum(), 1e-2)),
        "word_w": np.zeros((len(word_mass), h, IN_CLASS)), "word_b": np.maximum(np.log(share), -60),
    }
    params["inputs"][:, :h] += 1.0  # slow updates at first
    return {k: v.astype(np.float32) for k, v in params.items()}


def pack(params: dict[str, np.ndarray]) -> bytes:
    return b"".join(np.ascontiguousarray(params[k], np.float32).tobytes() for k in NAMES)


def unpack(raw: bytes, like: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    flat, out, at = np.frombuffer(raw, np.float32), {}, 0
    for k in NAMES:
        out[k] = flat[at : at + like[k].size].reshape(like[k].shape).copy()
        at += like[k].size
    return out


def lanes(lengths: list[int], n: int) -> list[list[int]]:
    """Texts dealt to at most n lanes of about equal length, longest first; lanes from the longest to the shortest."""
    heap = [(0, i) for i in range(max(1, min(n, len(lengths))))]
    out: list[list[int]] = [[] for _ in heap]
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        size, lane = heapq.heappop(heap)
        out[lane].append(i)
        heapq.heappush(heap, (size + lengths[i], lane))
    return sorted(out, key=lambda texts: -sum(lengths[i] for i in texts))


class Grid:
    """Texts as lanes: steps x lanes of codes, last codes, starts, and places in the texts laid end to end."""

    def __init__(self, texts: list[np.ndarray], n: int, piece: int | None = None):
        """``piece``: longest run of a text in a lane; a longer text is cut, and its later pieces start with an empty state behind their last code."""
        first = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
        units = [(i, a, min(a + (piece or len(t)), len(t))) for i, t in enumerate(texts) for a in range(0, len(t), piece or len(t))]
        dealt = [x for x in lanes([b - a for _, a, b in units], n) if x]
        self.length = np.array([sum(units[u][2] - units[u][1] for u in x) for x in dealt])
        shape = (int(self.length[0]) if len(dealt) else 0, len(dealt))
        self.code, self.last = np.zeros(shape, np.int32), np.zeros(shape, np.int32)
        self.start, self.place = np.zeros(shape, bool), np.zeros(shape, np.int64)
        for j, own in enumerate(dealt):
            at = 0
            for u in own:
                i, a, b = units[u]
                end = at + b - a
                self.code[at:end, j] = texts[i][a:b]
                self.last[at + 1 : end, j] = texts[i][a : b - 1]
                self.last[at, j] = texts[i][a - 1] if a else 0
                self.start[at, j] = True
                self.place[at:end, j] = np.arange(first[i] + a, first[i] + b)
                at = end

    def active(self, step: int) -> int:
        """Number of lanes that reach a step; lanes are sorted by length."""
        return int(np.searchsorted(-self.length, -step, "left"))


class Codes:
    """What a code stands for: its class and its place in the class (-1 in the tail)."""

    def __init__(self, cls: np.ndarray, place: np.ndarray):
        self.cls, self.place = cls.astype(np.int32), place.astype(np.int32)


#: Rows whose logits are held at once.
ROWS = 8192
#: States lie within -1 and 1, so logits are bounded by the weights; below this bound exp needs no shift by the maximum.
SAFE = 60.0


def is_safe(params: dict) -> bool:
    """Whether no logit can reach SAFE."""
    return max(float((np.abs(params[w]).sum(-2) + np.abs(params[b])).max(initial=0, where=params[b] > -59)) for w, b in (("class_w", "class_b"), ("word_w", "word_b"))) < SAFE


def _ranked(cls: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Places in the order of their classes, and where each of n classes starts; 16-bit keys are sorted by radix."""
    order = np.argsort(cls.astype(np.uint16) if n < 1 << 16 else cls, kind="stable")
    return order, np.searchsorted(cls[order], np.arange(n + 1))


def _with_one(h: np.ndarray) -> np.ndarray:
    """A column of ones beside the states, so that a product adds the bias."""
    out = np.empty((len(h), h.shape[1] + 1), h.dtype)
    out[:, :-1], out[:, -1] = h, 1
    return out


def _with_bias(w: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.concatenate([w, b[..., None, :]], -2)


def _masses(logit: np.ndarray, want: np.ndarray, safe: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of logits, which become their exponentials: the log probability of each row's wanted one, the row's sum, and the flat places of the wanted ones."""
    if not safe:
        logit -= logit.max(1, keepdims=True)
    at = np.arange(0, logit.size, logit.shape[1]) + want
    found = logit.ravel().take(at)
    np.exp(logit, out=logit)
    mass = logit @ np.ones(logit.shape[1], logit.dtype)
    found -= np.log(mass)
    return found, mass, at


def _head(params: dict, codes: Codes, target: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words of the head in the order of their classes: their places among the targets, where a class starts, their logits."""
    head = np.flatnonzero(codes.place[target] >= 0)
    word_w = _with_bias(params["word_w"], params["word_b"])
    order, cuts = _ranked(codes.cls[target[head]], len(word_w))
    head = head[order]
    own, logit = h[head], np.empty((len(head), word_w.shape[2]), h.dtype)
    for c in np.flatnonzero(np.diff(cuts)):
        np.matmul(own[cuts[c] : cuts[c + 1]], word_w[c], out=logit[cuts[c] : cuts[c + 1]])
    return head, cuts, logit


def output_logp(params: dict, codes: Codes, h: np.ndarray, target: np.ndarray, safe: bool = False) -> np.ndarray:
    """Natural log probability of each target: its class, and for the head its place in the class."""
    out = np.empty(len(h), h.dtype)
    for low in range(0, len(h), ROWS):
        wanted, own = target[low : low + ROWS], _with_one(h[low : low + ROWS])
        share = _masses(own @ _with_bias(params["class_w"], params["class_b"]), codes.cls[wanted], safe)[0]
        head, _, logit = _head(params, codes, wanted, own)
        share[head] += _masses(logit, codes.place[wanted[head]], safe)[0]
        out[low : low + ROWS] = share
    return out


class _Steps:
    """The cell, values by lanes: rows of a matrix are contiguous runs of lanes, so each operation is one loop."""

    def __init__(self, params: dict, last: np.ndarray, start: np.ndarray):
        self.steps, self.n = last.shape
        self.x = np.ascontiguousarray(params["inputs"][last].transpose(0, 2, 1))
        self.start = [np.flatnonzero(s) if some else () for s, some in zip(start, start.any(1).tolist(), strict=True)]
        self.recurrent = params["recurrent"]
        self.into = np.ascontiguousarray(self.recurrent.T)

    def __call__(self, t: int, prev: np.ndarray, gate: np.ndarray, cand: np.ndarray, g: np.ndarray, out: np.ndarray) -> None:
        """From the state ``prev``, which is cleared where a text starts: gates, candidate, products and the next state."""
        hid = len(prev)
        if len(self.start[t]):
            prev[:, self.start[t]] = 0
        np.matmul(self.into, prev, out=g)
        np.add(g[: 2 * hid], self.x[t, : 2 * hid], out=gate)
        np.negative(gate, out=gate)
        np.exp(gate, out=gate)
        gate += 1
        np.reciprocal(gate, out=gate)
        np.multiply(gate[hid:], g[2 * hid :], out=cand)
        cand += self.x[t, 2 * hid :]
        np.tanh(cand, out=cand)
        np.subtract(prev, cand, out=out)
        out *= gate[:hid]
        out += cand


def log_likelihood(params: dict, codes: Codes, texts: list[np.ndarray], window: int = 64) -> np.ndarray:
    """Natural log probability of every text, whole, the state carried across windows."""
    if not texts:
        return np.zeros(0)
    total, most = sum(map(len, texts)), max(map(len, texts))
    grid = Grid(texts, int(min(256, max(48, total // most))))
    logp, hid, safe = np.zeros(total), HIDDEN, is_safe(params)
    h = np.zeros((hid, grid.code.shape[1]), np.float32)
    for low in range(0, len(grid.code), window):
        up, n = min(low + window, len(grid.code)), grid.active(low)
        # A lane that ends inside the window runs on to its end; those steps are dropped.
        step = _Steps(params, grid.last[low:up, :n], grid.start[low:up, :n])
        held, h = np.empty((up - low, hid, n), np.float32), np.ascontiguousarray(h[:, :n])
        gate, cand, g = (np.empty((k * hid, n), np.float32) for k in (2, 1, 3))
        for t in range(up - low):
            step(t, h, gate, cand, g, held[t])
            h = held[t] if t + 1 == up - low or not len(step.start[t + 1]) else held[t].copy()
        inside = np.arange(low, up)[:, None] < grid.length[None, :n]
        logp[grid.place[low:up, :n][inside]] = output_logp(params, codes, held.transpose(0, 2, 1)[inside], grid.code[low:up, :n][inside], safe)
    first = np.concatenate([[0], np.cumsum([len(t) for t in texts])[:-1]])
    return np.add.reduceat(logp, first)


def gradients(params: dict, codes: Codes, code: np.ndarray, last: np.ndarray, start: np.ndarray, inside: np.ndarray, h: np.ndarray, safe: bool = False) -> tuple[float, dict, np.ndarray]:
    """Loss of a window (steps x lanes), its gradients, and the state after it. ``inputs`` comes as (rows, values)."""
    steps, n = code.shape
    hid, kind = HIDDEN, h.dtype
    step = _Steps(params, last, start)
    prev, gate, cand, g, out = (np.empty((steps, k * hid, n), kind) for k in (1, 2, 1, 3, 1))
    state = h.T
    for t in range(steps):
        prev[t] = state
        step(t, prev[t], gate[t], cand[t], g[t], out[t])
        state = out[t]
    full = bool(inside.all())
    rows = out.transpose(0, 2, 1)
    held, target = _with_one(rows.reshape(-1, hid) if full else rows[inside]), code[inside]
    cls = codes.cls[target]

    # Exponentials are not divided by their sums: the narrow factor of each product is.
    e, w = held @ _with_bias(params["class_w"], params["class_b"]), params["class_w"]
    found, mass, at = _masses(e, cls, safe)
    loss = -found.sum()
    e.ravel()[at] -= mass
    share = np.reciprocal(mass)
    d_class, d_class_b = (e.T @ (held[:, :hid] * share[:, None])).T, share @ e
    d_held = e @ w.T
    d_held *= share[:, None]

    w = params["word_w"]
    head, cuts, e = _head(params, codes, target, held)
    found, mass, at = _masses(e, codes.place[target[head]], safe)
    loss -= found.sum()
    e.ravel()[at] -= mass
    share = np.reciprocal(mass)
    own, d_own = held[head, :hid] * share[:, None], np.empty((len(head), hid), kind)
    d_word, d_word_b = np.zeros_like(w), np.zeros_like(params["word_b"])
    for c in np.flatnonzero(np.diff(cuts)):
        part = slice(cuts[c], cuts[c + 1])
        d_word[c] = (e[part].T @ own[part]).T
        np.matmul(share[part], e[part], out=d_word_b[c])
        np.matmul(e[part], w[c].T, out=d_own[part])
    d_own *= share[:, None]
    d_held[head] += d_own

    if full:
        d_rows = d_held.reshape(steps, n, hid)
    else:
        d_rows = np.zeros((steps, n, hid), kind)
        d_rows[inside] = d_held
    d_out = np.ascontiguousarray(d_rows.transpose(0, 2, 1))
    # Factors of all steps at once; what is left to a step is what hangs on the step behind it.
    z, r = gate[:, :hid], gate[:, hid:]
    by_cand, by_z, by_r = (1 - z) * (1 - cand * cand), (prev - cand) * z * (1 - z), g[:, 2 * hid :] * r * (1 - r)
    d_g, d_cand, d_h, carried = (np.empty(shape, kind) for shape in ((steps, 3 * hid, n), (steps, hid, n), (hid, n), (hid, n)))
    d_h[:] = 0
    for t in range(steps - 1, -1, -1):
        d_h += d_out[t]
        by, d_c = d_g[t], d_cand[t]
        np.multiply(d_h, by_cand[t], out=d_c)
        np.multiply(d_h, by_z[t], out=by[:hid])
        np.multiply(d_c, by_r[t], out=by[hid : 2 * hid])
        np.multiply(d_c, r[t], out=by[2 * hid :])
        np.matmul(step.recurrent, by, out=carried)
        d_h *= z[t]
        d_h += carried
        if len(step.start[t]):
            d_h[:, step.start[t]] = 0
    d_recurrent = np.matmul(prev, d_g.transpose(0, 2, 1)).sum(0)
    flat = last.ravel()
    order = np.argsort(flat.astype(np.uint16) if len(params["inputs"]) < 1 << 16 else flat, kind="stable")
    ranked = flat[order]
    first = np.flatnonzero(np.concatenate([[True], ranked[1:] != ranked[:-1]]))
    d_x = np.empty((steps, n, 3 * hid), kind)
    d_x[:, :, : 2 * hid], d_x[:, :, 2 * hid :] = d_g[:, : 2 * hid].transpose(0, 2, 1), d_cand.transpose(0, 2, 1)
    return float(loss), {
        "class_w": d_class, "class_b": d_class_b, "word_w": d_word, "word_b": d_word_b, "recurrent": d_recurrent,
        "inputs": (ranked[first], np.add.reduceat(d_x.reshape(-1, 3 * hid)[order], first, axis=0)),
    }, state.T


class Trainer:
    """Adagrad on the windows of the texts that it is given."""

    def __init__(self, params: dict[str, np.ndarray], codes: Codes, rate: float = 0.1):
        self.params, self.codes, self.rate, self.tokens, self.loss = params, codes, rate, 0, 0.0
        self.seen = {k: np.full_like(v, 1e-2) for k, v in params.items()}

    def fit(self, texts: list[np.ndarray]) -> None:
        grid = Grid(texts, LANES, PIECE)
        h = np.zeros((grid.code.shape[1], HIDDEN), np.float32)
        for low in range(0, len(grid.code), WINDOW):
            up, n = min(low + WINDOW, len(grid.code)), grid.active(low)
            part = (slice(low, up), slice(0, n))
            inside = np.arange(low, up)[:, None] < grid.length[None, :n]
            lost, grads, h = gradients(self.params, self.codes, grid.code[part], grid.last[part], grid.start[part], inside, h[:n], is_safe(self.params))
            count = int(inside.sum())
            self.tokens += count
            self.loss += lost
            self._step(grads, 1 / count**0.5)

    def _step(self, grads: dict, scale: float) -> None:
        rows, value = grads["inputs"]
        value = value * scale
        self.seen["inputs"][rows] += value * value
        self.params["inputs"][rows] -= self.rate * value / np.sqrt(self.seen["inputs"][rows])
        for k in NAMES[1:]:
            g = grads[k] * scale
            self.seen[k] += g * g
            self.params[k] -= self.rate * g / np.sqrt(self.seen[k])
