"""A small causal self-attention model over subword ids, in numpy: one attention layer, one feed-forward layer.

A place sees the rows of its own and, through a matrix, of the last subword; attention reaches back through the window. The
output is a softmax over classes of subwords, then one over the units of the class; every frequent subword is a unit of its
own, rare ones share units by frequency and divide them by their corpus counts. Classes hold about equal sums of square
roots of counts, so a place costs some tens of outputs however large the vocabulary is.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Window, tokens of context that a later window repeats, width, hidden width, classes, units, units shared by rare subwords, input rows, rows shared.
WINDOW, OVERLAP, WIDTH, HIDDEN, CLASSES, UNITS, SHARED_UNITS, ROWS, SHARED_ROWS = 32, 8, 24, 48, 16, 4096, 64, 4096, 64
#: Windows of a training step, the rate at the start and its part at the end, memories of the two moments.
BATCH, STEP, LAST, DECAY = 128, 0.03, 0.1, (0.9, 0.99)
#: Batches of windows whose outputs are scored at once.
TOGETHER = 4
_BEFORE = np.tril(np.ones((WINDOW, WINDOW), dtype=np.float32))
#: Attention logits lie within this, logits of outputs at most _DEEP below the greatest of their row: no exponential vanishes or
#: comes near the numbers that are slow.
_TOP, _DEEP = 30.0, 60.0
_TABLES = ("e", "t")


@dataclass
class Vocabulary:
    """Subword statistics: input row, output unit and class of each id, the log10 share of the id in its unit; bounds of the classes."""

    row: np.ndarray
    unit: np.ndarray
    cls: np.ndarray
    inside: np.ndarray
    bounds: np.ndarray
    mass: np.ndarray
    eos: int

    @classmethod
    def of(cls, counts: np.ndarray, eos: int) -> Vocabulary:
        counts = counts.astype(np.float64) + 0.5
        order = np.lexsort((np.arange(len(counts)), -counts))
        order = np.concatenate([[eos], order[order != eos]])
        rank = np.empty(len(counts), dtype=np.int64)
        rank[order] = np.arange(len(counts))
        own = UNITS - SHARED_UNITS
        # shared units of about equal mass
        rest, unit = order[own:], rank.copy()
        mass = np.cumsum(counts[rest])
        unit[rest] = own + np.minimum(SHARED_UNITS - 1, (mass * SHARED_UNITS / mass[-1]).astype(int)) if len(rest) else own
        total = np.bincount(unit, weights=counts, minlength=UNITS)
        root = np.cumsum(np.sqrt(total))
        klass = np.minimum(CLASSES - 1, ((root - np.sqrt(total) / 2) * CLASSES / root[-1]).astype(int))
        klass = np.unique(klass, return_inverse=True)[1]
        rows = ROWS - SHARED_ROWS
        row = np.where(rank < rows, rank, rows + np.arange(len(counts)) * 2654435761 % SHARED_ROWS)
        return cls(row.astype(np.uint16), unit.astype(np.uint16), klass[unit].astype(np.uint8), np.log10(counts / total[unit]), np.searchsorted(klass, np.arange(klass.max() + 2)), total, eos)


def start(vocabulary: Vocabulary, seed: int = 42) -> dict[str, np.ndarray]:
    """Small random weights; the outputs begin at the corpus shares. The last column of u and t is a bias."""
    rng, n = np.random.default_rng(seed), len(vocabulary.bounds) - 1
    w = {k: rng.normal(0, s, shape) for k, s, shape in (
        ("e", 0.3, (ROWS, WIDTH)), ("m", WIDTH**-0.5, (WIDTH, WIDTH)), ("p", 0.1, (WINDOW, WIDTH)), ("qkv", WIDTH**-0.5, (WIDTH, 3 * WIDTH)), ("o", WIDTH**-0.5, (WIDTH, WIDTH)),
        ("w1", WIDTH**-0.5, (WIDTH, HIDDEN)), ("b1", 0, (HIDDEN,)), ("w2", HIDDEN**-0.5, (HIDDEN, WIDTH)), ("u", WIDTH**-0.5, (n, WIDTH + 1)), ("t", 0.05, (UNITS, WIDTH + 1)),
    )}
    of = np.repeat(np.arange(n), np.diff(vocabulary.bounds))
    own = np.maximum(vocabulary.mass, 1e-6)  # of a small vocabulary some units have no members
    mass = np.bincount(of, weights=own)
    w["u"][:, -1], w["t"][:, -1] = np.log(mass / mass.sum()), np.log(own / mass[of])
    return {k: a.astype(np.float32) for k, a in w.items()}


def _flat(a: np.ndarray) -> np.ndarray:
    return a.reshape(-1, a.shape[-1])


def _products(w: dict[str, np.ndarray]) -> np.ndarray:
    """Queries times keys, scaled, beside values times outputs: with one head a place enters either pair only through its product."""
    qkv = w["qkv"]
    return np.hstack([qkv[:, :WIDTH] @ qkv[:, WIDTH : 2 * WIDTH].T * qkv.dtype.type(WIDTH**-0.5), qkv[:, 2 * WIDTH :] @ w["o"]])


def body(w: dict[str, np.ndarray], x: np.ndarray, begin: int = 0) -> tuple[np.ndarray, ...]:
    """Hidden states of windows of rows (windows x WINDOW) from a place on, and what the backward pass needs."""
    n = len(x)
    e = np.take(w["e"], x, axis=0, mode="clip")
    last = (_flat(e) @ w["m"]).reshape(e.shape)
    x0 = e + w["p"]
    x0[:, 1:] += last[:, :-1]
    ab = _products(w)
    av = (_flat(x0) @ ab).reshape(n, WINDOW, 2 * WIDTH)
    a, v = av[:, begin:, :WIDTH], av[..., WIDTH:]
    s = a @ x0.transpose(0, 2, 1)
    if s.max() > _TOP or s.min() < -_TOP:  # a look at the extremes is cheap, a comparison with each is not
        np.clip(s, -_TOP, _TOP, out=s)
    np.exp(s, out=s)
    s *= _BEFORE[begin:]
    s /= s @ np.ones((WINDOW, 1), dtype=s.dtype)
    c = s @ v
    h = _flat(c + x0[:, begin:])
    g = h @ w["w1"]
    g += w["b1"]
    np.maximum(g, 0, out=g)
    h2 = np.empty((len(h), WIDTH + 1), dtype=h.dtype)
    np.add(g @ w["w2"], h, out=h2[:, :WIDTH])
    h2[:, WIDTH] = 1
    return e, x0, ab, a, v, s, c, h, g, h2


class Windows:
    """Windows over sequences, each closed by the end id and opened by it too; every target is scored in exactly one window.

    Only three numbers a window are kept; what a batch needs is taken from the sequences.
    """

    def __init__(self, sequences: list[np.ndarray], vocabulary: Vocabulary, overlap: int = OVERLAP) -> None:
        length = np.array([len(s) + 1 for s in sequences], dtype=np.int64)
        end = np.array([vocabulary.eos], dtype=np.uint16)
        self.flat = np.concatenate([a for s in sequences for a in (end, s)] + [end])
        self.rows, self.overlap = vocabulary.row, overlap
        stride = WINDOW - overlap
        n = np.maximum(1, -(-(length - overlap) // stride))
        self.number = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        begins = np.cumsum(length) - length
        self.first = np.repeat(begins, n) + self.number * stride
        self.last = np.repeat(begins + length, n)

    def __len__(self) -> int:
        return len(self.first)

    def take(self, which: np.ndarray | slice) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(rows, scored, targets) of some windows."""
        at = self.first[which][:, None] + np.arange(WINDOW)
        inside = at < self.last[which][:, None]
        scored = inside & ((self.number[which] == 0)[:, None] | (np.arange(WINDOW) >= self.overlap))
        np.minimum(at, len(self.flat) - 2, out=at)
        # the next input is the target; the opening end of the next sequence closes this one
        return np.where(inside, self.rows[self.flat[at]], 0), scored, self.flat[at + 1]


def _softmax(h: np.ndarray, table: np.ndarray, own: np.ndarray, scale: float | None) -> tuple[np.ndarray, np.ndarray]:
    """(natural logs of the probabilities of the own outputs, gradients of the logits times scale, outputs x places).

    Places lie along the rows, so that the reductions over the few outputs run over whole vectors.
    """
    z = table @ h.T
    if z.size and max(z.max(), -z.min()) > _DEEP / 2:  # else none is so far below its row's greatest
        z -= z.max(axis=0)
        np.maximum(z, -_DEEP, out=z)
    at = own * z.shape[1] + np.arange(z.shape[1])
    logit = z.ravel()[at]
    np.exp(z, out=z)
    total = z.sum(axis=0)
    if scale is not None:
        z *= z.dtype.type(scale) / total
        z.ravel()[at] -= z.dtype.type(scale)
    return logit - np.log(total), z


def outputs(w: dict[str, np.ndarray], h: np.ndarray, ids: np.ndarray, vocabulary: Vocabulary, scale: float | None = None, keep: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray | None, dict]:
    """(natural logs of the probabilities of the ids' units, gradients of h and of u and t); the latter two if a scale is given.

    The ids belong to the rows keep of h, or to all. Places are sorted by class, so a class's units meet all their places in one product.
    """
    order = np.argsort(vocabulary.cls[ids], kind="stable")
    rows = order if keep is None else keep[order]
    whole, h, ids = len(h), np.take(h, rows, axis=0, mode="clip"), ids[order]
    cls, unit = vocabulary.cls[ids], vocabulary.unit[ids].astype(np.int64)
    log, z = _softmax(h, w["u"], cls.astype(np.int64), scale)
    grads, dh = {}, None
    if scale is not None:
        grads = {"u": z @ h, "t": np.zeros_like(w["t"])}
        dh = z.T @ w["u"][:, :WIDTH]
    ends, a = np.cumsum(np.bincount(cls, minlength=len(vocabulary.bounds) - 1)), 0
    for k, b in enumerate(ends):
        s, e = vocabulary.bounds[k], vocabulary.bounds[k + 1]
        if b > a and e - s > 1:
            more, y = _softmax(h[a:b], w["t"][s:e], unit[a:b] - s, scale)
            log[a:b] += more
            if scale is not None:
                np.matmul(y, h[a:b], out=grads["t"][s:e])
                dh[a:b] += y.T @ w["t"][s:e, :WIDTH]
        a = b
    told = np.empty_like(log)
    told[order] = log
    if dh is None:
        return told, None, grads
    back = np.zeros((whole, WIDTH), dtype=dh.dtype)
    back[rows] = dh
    return told, back, grads


def log10_tokens(w: dict[str, np.ndarray], sequences: list[np.ndarray], vocabulary: Vocabulary, batch: int = BATCH) -> np.ndarray:
    """log10 of the probability of every token and of the end of each sequence, in order.

    Hidden states are made for a batch of windows; the outputs, a class at a time, take several batches at once. Of a later
    window the places that it repeats are only looked back at, so their hidden states aren't made.
    """
    every = Windows(sequences, vocabulary)
    begin = np.where(every.number == 0, 0, every.overlap)
    n = np.minimum(every.last - every.first, WINDOW) - begin
    start, out = np.cumsum(n) - n, np.empty(int(n.sum()))
    h, ids, at = [], [], []

    def settle() -> None:
        if h:
            told, own = outputs(w, np.concatenate(h), i := np.concatenate(ids), vocabulary)[0], vocabulary.inside[i]
            out[np.concatenate(at)] = told / np.log(10) + own
            for a in (h, ids, at):
                a.clear()

    for b in (0, every.overlap) if every.overlap else (0,):
        group = np.flatnonzero(begin == b)
        for i in range(0, len(group), batch):
            which = group[i : i + batch]
            x, scored, targets = every.take(which)
            scored = scored[:, b:]
            hidden = body(w, x, b)[-1]
            h.append(hidden if scored.all() else hidden[scored.ravel()])
            ids.append(targets[:, b:][scored])
            at.append((start[which][:, None] + np.arange(WINDOW - b))[scored])
            if len(h) == TOGETHER:
                settle()
    settle()
    return out


def log10_probabilities(w: dict[str, np.ndarray], sequences: list[np.ndarray], vocabulary: Vocabulary) -> np.ndarray:
    """log10 of the probability of each sequence with its end."""
    owner = np.repeat(np.arange(len(sequences)), [len(s) + 1 for s in sequences])
    return np.bincount(owner, weights=log10_tokens(w, sequences, vocabulary), minlength=len(sequences))


def _by_row(rows: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(distinct rows, sums of their gradients)."""
    order = np.argsort(rows, kind="stable")
    s = rows[order]
    first = np.flatnonzero(np.r_[True, s[1:] != s[:-1]])
    return s[first], np.add.reduceat(np.take(g, order, axis=0, mode="clip"), first, axis=0)


def gradients(w: dict[str, np.ndarray], x: np.ndarray, targets: np.ndarray, scored: np.ndarray, vocabulary: Vocabulary) -> tuple[float, dict[str, np.ndarray], np.ndarray]:
    """Mean log loss of the units and its gradients; that of e for the distinct rows, which come last."""
    e, x0, ab, a, v, s, c, h, g, h2 = body(w, x)
    keep = np.flatnonzero(scored)
    log, dh2, d = outputs(w, h2, targets.ravel()[keep], vocabulary, 1 / max(1, len(keep)), keep)
    d["w2"] = g.T @ dh2
    dr = dh2 @ w["w2"].T
    dr *= np.sign(g)  # g is not negative
    d["w1"], d["b1"] = h.T @ dr, np.ones(len(dr), dtype=dr.dtype) @ dr
    dh = dr @ w["w1"].T
    dh += dh2
    dc = dh.reshape(c.shape)
    ds = dc @ v.transpose(0, 2, 1)
    ds -= np.einsum("ntw,ntw->nt", dc, c)[..., None]
    ds *= s
    dav = np.empty((len(x), WINDOW, 2 * WIDTH), dtype=s.dtype)
    np.matmul(ds, x0, out=dav[..., :WIDTH])
    np.matmul(s.transpose(0, 2, 1), dc, out=dav[..., WIDTH:])
    dab = _flat(x0).T @ _flat(dav)
    dqk, dvo, qkv = dab[:, :WIDTH] * s.dtype.type(WIDTH**-0.5), dab[:, WIDTH:], w["qkv"]
    d["qkv"] = np.hstack([dqk @ qkv[:, WIDTH : 2 * WIDTH], dqk.T @ qkv[:, :WIDTH], dvo @ w["o"].T])
    d["o"] = qkv[:, 2 * WIDTH :].T @ dvo
    dx = (_flat(dav) @ ab.T).reshape(x0.shape)
    dx += dc
    dx += ds.transpose(0, 2, 1) @ a
    d["p"] = dx.sum(axis=0)
    later = np.zeros_like(dx)  # the next place's
    later[:, :-1] = dx[:, 1:]
    d["m"] = _flat(e).T @ _flat(later)
    de = _flat(later) @ w["m"].T
    de += _flat(dx)
    rows, d["e"] = _by_row(x.ravel(), de)
    return -float(log.mean()) if len(log) else 0.0, d, rows


class Trainer:
    """Weights under training: two moments for the small matrices, one moment a row for the two tables."""

    def __init__(self, w: dict[str, np.ndarray], vocabulary: Vocabulary, expected: int, step: float = STEP, seed: int = 42) -> None:
        """expected: windows to come; the rate falls evenly over them."""
        self.w, self.vocabulary, self.expected, self.step = {k: a.copy() for k, a in w.items()}, vocabulary, max(1, expected), step
        self.first = {k: np.zeros_like(a) for k, a in w.items() if k not in _TABLES}
        self.second = {k: np.zeros(len(a) if k in _TABLES else a.shape, dtype=np.float32) for k, a in w.items()}
        self.rng, self.steps, self.seen, self.losses = np.random.default_rng(seed), 0, 0, []

    def feed(self, sequences: list[np.ndarray]) -> None:
        """One pass over the windows of these sequences, every token once."""
        if not sequences:
            return
        every = Windows(sequences, self.vocabulary, 0)
        order = self.rng.permutation(len(every))
        for i in range(0, len(order), BATCH):
            at = order[i : i + BATCH]
            x, scored, targets = every.take(at)
            self._step(*gradients(self.w, x, targets, scored, self.vocabulary))
            self.seen += len(at)

    def _step(self, loss: float, d: dict[str, np.ndarray], rows: np.ndarray) -> None:
        self.losses.append(loss)
        self.steps += 1
        a, b = np.float32(1 - DECAY[0]), np.float32(1 - DECAY[1])
        rate = np.float32(self.step * max(LAST, 1 - (1 - LAST) * self.seen / self.expected))
        early = np.float32(1 - DECAY[0] ** self.steps), np.float32(1 - DECAY[1] ** self.steps)
        for k, w in self.w.items():
            g, v = d[k], self.second[k]
            if k in _TABLES:
                at = rows if k == "e" else slice(None)
                v[at] += b * (np.einsum("ij,ij->i", g, g) / np.float32(g.shape[1]) - v[at])
                w[at] -= g * (rate / (np.sqrt(v[at] / early[1]) + np.float32(1e-8)))[:, None]
            else:
                m = self.first[k]
                m += a * (g - m)
                v += b * (g * g - v)
                w -= rate / early[0] * m / (np.sqrt(v / early[1]) + np.float32(1e-8))


def pack(w: dict[str, np.ndarray]) -> np.ndarray:
    return np.concatenate([w[k].ravel() for k in sorted(w)])


def unpack(flat: np.ndarray, like: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    at, out = 0, {}
    for k in sorted(like):
        out[k] = flat[at : at + like[k].size].reshape(like[k].shape).astype(np.float32)
        at += like[k].size
    return out
