"""A small causal self-attention language model on subword ids, trained in numpy.

Codes: the most frequent subword ids of the corpus, one code for all others (an id among those then has
its smoothed share of the corpus), one for the beginning. A position predicts the next code from the
last two codes and from masked attention over its window (relative-position bias); the output is a
two-level softmax, classes then members, so a token costs two short softmaxes. The prediction is mixed
by a learned gate with bigram shares counted over the whole training corpus: a proper distribution.
Long texts are scored by overlapping windows; each token is scored in exactly one.
"""

from __future__ import annotations

import numpy as np

from meshprofile.llm.learning import Adam, sigmoid

HEAD, CLASSES, WINDOW, CONTEXT, DIM, KEYS, BATCH = 1023, 32, 32, 8, 32, 8, 256
RARE, BEGIN, CODES = HEAD, HEAD + 1, HEAD + 2
MEMBERS = (HEAD + 1) // CLASSES
MANY = 16
#: Windows that attention takes at a time, and numbers that a step of Adam takes at a time.
BLOCK, STRETCH = 32, 1 << 14


def classes_of(bigrams: np.ndarray) -> np.ndarray:
    """Class of each code: codes are split in equal halves by the main direction of what precedes them, again and again."""
    share = np.log1p(bigrams[:, : HEAD + 1].T)
    share /= np.linalg.norm(share, axis=1, keepdims=True) + 1e-9
    groups = [np.arange(HEAD + 1)]
    while len(groups) < CLASSES:
        split = []
        for g in groups:
            x = share[g] - share[g].mean(0)
            v = np.linspace(-1, 1, x.shape[1]) + 0.1
            for _ in range(30):
                v = x.T @ (x @ v)
                v /= np.linalg.norm(v) + 1e-12
            order = np.argsort(x @ v, kind="stable")
            split += [np.sort(g[order[: len(g) // 2]]), np.sort(g[order[len(g) // 2 :]])]
        groups = split
    out = np.zeros(HEAD + 1, np.int64)
    for i, g in enumerate(groups):
        out[g] = i
    return out


def windows_of(ends: np.ndarray, step: int = WINDOW - CONTEXT) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For texts end to end with n + 1 offsets (none empty): start and text of each window, and how many
    leading places of it an earlier window has scored."""
    n = np.diff(ends)
    count = 1 + -(-np.maximum(n - WINDOW, 0) // step)
    owner = np.repeat(np.arange(len(n)), count)
    k = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)
    return ends[owner] + k * step, owner, np.where(k > 0, CONTEXT, 0)


def summed_rows(index: np.ndarray, rows: np.ndarray, most: int) -> np.ndarray:
    """(most, width): the sums of the rows (float32) that `index` gives the same number below `most`."""
    out, n = np.zeros((most, rows.shape[1]), np.float32), np.bincount(index, minlength=most)
    # numbers in the order of how many rows they have: those with equally many add up as one block
    by = np.argsort(n, kind="stable")
    rank = np.empty(most, np.uint16)
    rank[by] = np.arange(most)
    rows, n = rows.take(np.argsort(rank.take(index), kind="stable"), 0), n[by]
    ends, sums, few = np.cumsum(n), np.zeros_like(out), int(np.searchsorted(n, MANY))
    cuts = np.searchsorted(n[:few], np.arange(1, MANY + 1))
    for c, (i, j) in enumerate(zip(cuts[:-1].tolist(), cuts[1:].tolist()), 1):
        if j > i:
            block = rows[ends[i] - c : ends[j - 1]].reshape(j - i, c, -1)
            np.add.reduce(block, 1, out=sums[i:j])
    ones = np.ones(n.max(initial=0), np.float32)
    for i in range(few, most):  # many rows add up as a product with ones
        np.matmul(ones[: n[i]], rows[ends[i] - n[i] : ends[i]], out=sums[i])
    out[by] = sums
    return out


def row_sums(x: np.ndarray) -> np.ndarray:
    """Sums along the short last axis, as a product with ones."""
    return x @ np.ones(x.shape[-1], x.dtype)


def exp_of(x: np.ndarray) -> np.ndarray:
    """In place, e to the power of x, or of 60 if that is less; to look for the largest first is cheaper than to cap each."""
    if x.size and not x.max() <= 60:
        np.minimum(x, 60, out=x)
    return np.exp(x, out=x)


def tanh_of(x: np.ndarray) -> np.ndarray:
    """In place, the hyperbolic tangent: one pass, where 2 / (1 + exp(-2 x)) - 1 takes five."""
    return np.tanh(x, out=x)


def turned(x: np.ndarray) -> np.ndarray:
    """Each matrix transposed and laid out anew, which batched products are much faster with."""
    return np.ascontiguousarray(x.transpose(0, 2, 1))


class AttentionLM:
    def __init__(self, code_class: np.ndarray, seed: int = 9):
        rng = np.random.default_rng(seed)
        self.code_class = code_class
        order = np.argsort(code_class, kind="stable")
        self.member = np.empty(HEAD + 1, np.int64)
        self.member[order] = np.arange(HEAD + 1) % MEMBERS
        self.p = {
            "q": rng.normal(0, 0.5, (CODES, KEYS)),
            "k": rng.normal(0, 0.5, (CODES, KEYS)),
            "v": rng.normal(0, 0.3, (CODES, DIM)),
            "one": rng.normal(0, 0.5, (CODES, DIM)),
            "two": rng.normal(0, 0.3, (CODES, DIM)),
            "near": np.linspace(1, -1, WINDOW),
            "wc": rng.normal(0, 0.3, (DIM, CLASSES)),
            "bc": np.zeros(CLASSES),
            "wm": rng.normal(0, 0.3, (CLASSES, DIM, MEMBERS)),
            "bm": np.zeros((CLASSES, MEMBERS)),
            "gate": np.full(CODES, 0.5),
        }
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}
        self.bigram = self.left_out = np.full((CODES, HEAD + 1), 1 / (HEAD + 1), np.float32)
        i = np.arange(WINDOW)
        self.back = np.maximum(i[:, None] - i, 0)
        self.mask = (i[:, None] >= i).astype(np.float32)

    def set_bigrams(self, counts: np.ndarray) -> None:
        """counts[code before, code]: shares with unigram back-off (Witten-Bell)."""
        uni = counts[:, : HEAD + 1].sum(0) + 0.5
        uni /= uni.sum()
        kinds = np.maximum((counts > 0).sum(1, keepdims=True), 1)
        whole = counts.sum(1, keepdims=True)
        self.bigram = ((counts + kinds * uni) / (whole + kinds)).astype(np.float32)
        # the same without one occurrence of the pair, for training
        self.left_out = (np.maximum(counts - 1, 0) + kinds * uni).astype(np.float32) / np.maximum(whole - 1 + kinds, 1).astype(np.float32)

    def outputs(self) -> tuple[np.ndarray, np.ndarray]:
        """Weights and biases of every class: those of the classes and, beside them, those of its members."""
        p = self.p
        weights = np.concatenate([np.broadcast_to(p["wc"], (CLASSES, DIM, CLASSES)), p["wm"]], 2)
        return weights, np.concatenate([np.broadcast_to(p["bc"], (CLASSES, CLASSES)), p["bm"]], 1)

    def attend(self, x: np.ndarray, low: int = 0):
        """Queries, keys, values, weights and context of the windows' places from `low` on; a few windows at a time,
        so that what they need stays in the processor's cache."""
        p, n = self.p, len(x)
        q, k, v = p["q"].take(x[:, low:], 0), p["k"].take(x, 0), p["v"].take(x, 0)
        a, context = np.empty((n, WINDOW - low, WINDOW), np.float32), np.empty((n, WINDOW - low, DIM), np.float32)
        bias = np.where(self.mask > 0, p["near"][self.back], np.float32(-1e4))[low:]
        for i in range(0, n, BLOCK):
            s = slice(i, i + BLOCK)
            part = np.matmul(q[s], turned(k[s]), out=a[s])
            part += bias
            exp_of(part)
            part /= row_sums(part)[..., None]
            np.matmul(part, v[s], out=context[s])
        return q, k, v, a, context.reshape(-1, DIM)

    def hidden(self, x: np.ndarray, before: np.ndarray, context: np.ndarray, y: np.ndarray, use: np.ndarray):
        """Of the places `use`, in the order of the classes of what they predict: their numbers, codes, classes' cuts,
        what they predict and hidden units."""
        cls = self.code_class.take(y.take(use))
        order = np.argsort(cls.astype(np.uint8), kind="stable")
        use, cuts = use.take(order), np.searchsorted(cls.take(order), np.arange(CLASSES + 1)).tolist()
        x1, y1 = x.take(use), y.take(use)
        h = context.take(use, 0)
        h += self.p["one"].take(x1, 0)
        h += self.p["two"].take(before.take(use), 0)
        return use, x1, y1, cuts, tanh_of(h)

    def forward(self, x: np.ndarray, before: np.ndarray, y: np.ndarray, skip: np.ndarray):
        """x: codes of each window's places (windows, WINDOW); before: the code two back from what a place
        predicts; y: what it predicts, -1 beyond the end; skip: leading places not to be scored.
        Gives the places scored (flat) and the natural log of their shares."""
        low = int(skip.min()) if len(skip) else 0  # no window asks for places before this one
        context = self.attend(x, low)[-1]
        x, before, y = x[:, low:], before[:, low:], y[:, low:]
        use = np.flatnonzero(((y >= 0) & (np.arange(low, WINDOW) >= skip[:, None])).ravel())
        use, x1, y1, cuts, h = self.hidden(x.ravel(), before.ravel(), context, y.ravel(), use)
        weights, biases = self.outputs()
        share, member, room = np.empty(len(use), np.float32), self.member.take(y1), self.room(cuts)
        for c in range(CLASSES):
            s = slice(cuts[c], cuts[c + 1])
            if s.stop > s.start:
                e, sums, named = self.likely(h[s], weights[c], biases[c], member[s], room)
                np.multiply(e[:, c], e.ravel().take(named), out=share[s])
                share[s] /= sums[:, 0] * sums[:, 1]
        g = sigmoid(self.p["gate"])
        share *= g.take(x1)
        share += (1 - g).take(x1) * self.bigram.take(x1 * np.int64(HEAD + 1) + y1)
        return use if not low else use + low * (use // (WINDOW - low) + 1), np.log(share)

    @staticmethod
    def room(cuts: list[int]) -> tuple[np.ndarray, np.ndarray]:
        """Room for the outputs of a class's places, and where the members of each begin in it."""
        most = max(np.diff(cuts))
        return np.empty((most, CLASSES + MEMBERS), np.float32), np.arange(CLASSES, most * (CLASSES + MEMBERS), CLASSES + MEMBERS)

    @staticmethod
    def likely(h: np.ndarray, weights: np.ndarray, biases: np.ndarray, member: np.ndarray, room: tuple[np.ndarray, np.ndarray]):
        """Of places that predict one class: the exponentials of classes and members beside each other, the sums of both,
        and where those of the members named stand. All of a class is done at once, while it is in the cache."""
        e = np.matmul(h, weights, out=room[0][: len(h)])
        e += biases
        exp_of(e)
        return e, row_sums(e.reshape(-1, MEMBERS)).reshape(-1, 2), room[1][: len(h)] + member

    def gradients(self, x: np.ndarray, before: np.ndarray, y: np.ndarray) -> tuple[dict[str, np.ndarray], float]:
        """Of minus the mean log share, and that mean. Beyond a window's first place, `before` must be what x is one place earlier."""
        p = self.p
        q, k, v, a, context = self.attend(x)
        use, x1, y1, cuts, h = self.hidden(x.ravel(), before.ravel(), context, y.ravel(), np.flatnonzero(y.ravel() >= 0))
        n, gate = len(use), sigmoid(p["gate"])
        g = gate.take(x1)
        mixed = (1 - gate).take(x1) * self.left_out.take(x1 * np.int64(HEAD + 1) + y1)
        weights, biases = self.outputs()
        turned_weights = turned(weights)
        post, dh, ones = np.empty(n, np.float32), np.empty_like(h), np.ones(n, np.float32)
        dw, db = np.zeros_like(weights), np.zeros((CLASSES, CLASSES + MEMBERS), np.float32)
        member, room = self.member.take(y1), self.room(cuts)
        for c in range(CLASSES):
            s = slice(cuts[c], cuts[c + 1])
            if s.stop > s.start:
                e, sums, named = self.likely(h[s], weights[c], biases[c], member[s], room)
                own = e[:, c] * e.ravel().take(named)
                own /= sums[:, 0] * sums[:, 1]
                own *= g[s]
                mixed[s] += own
                own = np.divide(own, mixed[s], out=post[s])  # how much of the share the network accounts for
                own = own * np.float32(1 / n)
                halves = e.reshape(-1, 2, MEMBERS)
                halves *= (own[:, None] / sums)[..., None]
                e[:, c] -= own
                e.ravel()[named] -= own
                np.matmul(h[s].T, e, out=dw[c])
                np.matmul(ones[s], e, out=db[c])
                np.matmul(e, turned_weights[c], out=dh[s])
        out = {"gate": np.bincount(x1, (g - post) / n, CODES)}
        out |= {"wc": dw[:, :, :CLASSES].sum(0), "bc": db[:, :CLASSES].sum(0), "wm": dw[:, :, CLASSES:], "bm": db[:, CLASSES:]}
        h *= h
        dh *= np.subtract(1, h, out=h)
        # what a place's code gets by itself, for the next place, as a value, a query and a key: added in one go, with
        # what the codes before the windows get for the first places
        names = ("one", "two", "v", "q", "k")
        ends = np.cumsum([p[c].shape[1] for c in names])
        rows = np.empty((x.size + len(x), ends[-1]), np.float32)
        one, two, value, query, key = np.split(rows[: x.size].reshape(*x.shape, -1), ends[:-1], 2)
        dc = context  # no longer needed: its room is used again
        if n < x.size:
            dc[:] = 0
        dc[use] = dh
        dc, near = dc.reshape(*x.shape, DIM), np.zeros((WINDOW, WINDOW), np.float32)
        for i in range(0, len(x), BLOCK):
            s = slice(i, i + BLOCK)
            d, w = dc[s], a[s]
            ds = d @ turned(v[s])
            ds -= np.einsum("wij,wij->wi", w, ds)[..., None]
            ds *= w  # zero above the diagonal, as the weights are there
            near += ds.sum(0)
            one[s] = d
            two[s, :-1], two[s, -1] = d[:, 1:], 0
            np.matmul(w.transpose(0, 2, 1), d, out=value[s])
            np.matmul(ds, k[s], out=query[s])
            np.matmul(ds.transpose(0, 2, 1), q[s], out=key[s])
        rows[x.size :] = 0
        rows[x.size :, ends[0] : ends[1]] = dc[:, 0]
        sums = summed_rows(np.r_[x.ravel(), before[:, 0]], rows, CODES)
        out |= dict(zip(names, np.split(sums, ends[:-1], 1)))
        out["near"] = np.bincount(self.back.ravel(), near.ravel(), WINDOW)
        return {c: val.astype(np.float32, copy=False) for c, val in out.items()}, float(np.log(mixed).mean())

    @staticmethod
    def earlier(codes: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The codes one and two places before each, BEGIN before a text's first."""
        shifted, again = np.empty_like(codes), np.empty_like(codes)
        shifted[1:] = codes[:-1]
        shifted[ends[:-1]] = BEGIN
        again[1:] = shifted[:-1]
        again[ends[:-1]] = BEGIN
        return shifted, again

    @staticmethod
    def arrays(codes: np.ndarray, before: tuple[np.ndarray, np.ndarray], ends: np.ndarray, starts: np.ndarray, owner: np.ndarray):
        """Window matrices over texts of codes end to end (each with its end token)."""
        at = starts[:, None] + np.arange(WINDOW)
        inside = at < ends[owner + 1][:, None]
        at = np.minimum(at, len(codes) - 1)
        return before[0].take(at), before[1].take(at), np.where(inside, codes.take(at), -1)

    def log10_shares(self, codes: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Log10 probability of each text of codes end to end."""
        starts, owner, skip = windows_of(ends)
        out, before = np.zeros(len(ends) - 1), self.earlier(codes, ends)
        # a text's first windows apart from later ones, whose leading places are scored already
        for some in (skip == 0, skip > 0):
            at, whose, part = starts[some], owner[some], skip[some]
            for i in range(0, len(at), BATCH):
                s = slice(i, i + BATCH)
                use, ll = self.forward(*self.arrays(codes, before, ends, at[s], whose[s]), part[s])
                first = whose[i]
                here = np.bincount(whose[s].take(use // WINDOW) - first, ll.astype(np.float64))
                out[first : first + len(here)] += here
        return out / np.log(10)


def bigram_counts(codes: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Flat counts of (code before, code) over texts of codes end to end."""
    shifted = np.empty_like(codes)
    shifted[1:] = codes[:-1]
    shifted[ends[:-1]] = BEGIN
    return np.bincount(shifted.astype(np.int64) * (HEAD + 1) + codes, minlength=CODES * (HEAD + 1))


class FlatAdam:
    """learning.Adam without decay over all parameters end to end, a stretch of the cache's size at a time. The
    parameters of `net` become views of one array."""

    def __init__(self, net: AttentionLM, rate: float):
        self.rate, self.t, like = rate, 0, net.p
        self.p = pack(like)
        self.m, self.v, self.g = (np.zeros_like(self.p) for _ in range(3))
        self.free = np.empty((2, STRETCH), np.float32)
        net.p, self.grads = views(self.p, like), views(self.g, like)

    def step(self, grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            self.grads[k][...] = g
        # m / first / (sqrt(v / second) + 1e-8), with both divisions by numbers moved out
        first, second = 1 - 0.9**self.t, (1 - 0.99**self.t) ** 0.5
        rate, least = np.float32(self.rate * second / first), np.float32(1e-8 * second)
        for i in range(0, len(self.p), STRETCH):
            p, m, v, g = (x[i : i + STRETCH] for x in (self.p, self.m, self.v, self.g))
            a, b = self.free[:, : len(p)]
            np.subtract(g, m, out=a)
            a *= np.float32(0.1)
            m += a
            g *= g
            g -= v
            g *= np.float32(0.01)
            v += g
            np.sqrt(v, out=a)
            a += least
            np.multiply(m, rate, out=b)
            b /= a
            p -= b


class Learner:
    """Goes once over all windows of the texts it is given, from the parameters it starts with; what
    learners reach is averaged by the windows they saw. Needs net.left_out."""

    def __init__(self, net: AttentionLM, rate: float = 0.002, batch: int = 256, seed: int = 9):
        self.net, self.batch, self.rng, self.seen = net, batch, np.random.default_rng(seed), 0
        self.adam = FlatAdam(net, rate)

    def learn(self, codes: np.ndarray, ends: np.ndarray) -> None:
        starts, owner, _ = windows_of(ends, WINDOW)
        before, order = self.net.earlier(codes, ends), self.rng.permutation(len(starts))
        for i in range(0, len(order), self.batch):
            pick = order[i : i + self.batch]
            self.adam.step(self.net.gradients(*self.net.arrays(codes, before, ends, starts[pick], owner[pick]))[0])
        self.seen += len(starts)

    def packed(self) -> np.ndarray:
        return pack(self.net.p)


def pack(p: dict[str, np.ndarray]) -> np.ndarray:
    return np.concatenate([p[k].ravel() for k in sorted(p)])


def views(flat: np.ndarray, like: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    """The parts of a packed array, in the shapes of `like`."""
    cuts = np.cumsum([like[k].size for k in sorted(like)])[:-1]
    return {k: v.reshape(like[k].shape) for k, v in zip(sorted(like), np.split(flat, cuts))}


def unpack(flat: np.ndarray, like: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    return {k: v.astype(np.float32) for k, v in views(flat, like).items()}


def train(codes: np.ndarray, ends: np.ndarray, steps: int = 600, epochs: int = 6, batch: int = 64, rate: float = 0.02, seed: int = 9, whole: np.ndarray | None = None) -> AttentionLM:
    """Network and gate learn beside bigram shares that leave the predicted pair itself out of their counts
    (`whole`, those of the texts if not given)."""
    whole = bigram_counts(codes, ends).reshape(CODES, HEAD + 1) if whole is None else whole
    net = AttentionLM(classes_of(whole), seed)
    net.set_bigrams(whole)
    uni = np.log(whole.sum(0) + 0.5)
    for c in range(CLASSES):
        own = np.flatnonzero(net.code_class == c)
        net.p["bc"][c] = np.log(np.exp(uni[own]).sum()) - np.log(np.exp(uni).sum()) + 3
        net.p["bm"][c, net.member[own]] = uni[own] - uni[own].mean()
    adam, rng = Adam(net.p, rate), np.random.default_rng(seed)
    starts, owner, _ = windows_of(ends, WINDOW)
    before = net.earlier(codes, ends)
    steps = min(steps, -(-epochs * len(starts) // batch))
    for step in range(steps):
        adam.rate = rate * (1 - step / steps) + rate / 20
        pick = rng.integers(0, len(starts), batch)
        adam.step(net.gradients(*net.arrays(codes, before, ends, starts[pick], owner[pick]))[0])
    return net
