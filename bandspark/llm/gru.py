"""A gated recurrent language model with a class-factored output, in numpy.

Token ids: 0 .. head - 1 are the frequent words in classes of ``per_class``; head .. head + tails - 1 stand for the tail
classes, whose words the model does not tell apart. P(token) = P(class | state) * P(word in class | state) for
frequent words, and P(class | state) for tail ids (the caller adds the share of the word in its class).
"""

from __future__ import annotations

import heapq

import numpy as np

F = np.float32
clip = getattr(np, "_core", None) and np._core.umath.clip or np.clip  # np.clip without its wrappers, which cost as much as a small array
#: Steps that one pass should have, and lanes it has at least.
STEPS, LEAST_LANES = 250, 16
#: Rows of logits made at once; bound of a logit.
ROWS, LOGITS = 2048, 60


class Gru:
    def __init__(self, head: int, tails: int, per_class: int, hidden: int, counts: np.ndarray, seed: int = 5):
        """counts: of all ids, for output biases that start as the unigram model."""
        self.head, self.tails, self.per, self.hidden = head, tails, per_class, hidden
        self.head_classes = -(-head // per_class)
        self.classes = self.head_classes + tails
        rng = np.random.default_rng(seed)
        n = head + tails
        c = np.maximum(counts.astype(float), 0.5)
        padded = np.zeros(self.head_classes * per_class)
        padded[:head] = c[:head]
        mass = np.concatenate([padded.reshape(-1, per_class).sum(axis=1), c[head:]])
        small = 0.1
        self.p = {
            "g": rng.normal(0, small, (n + 1, 3 * hidden)).astype(F),  # the last row starts a document
            "u": rng.normal(0, small, (hidden, 3 * hidden)).astype(F),
            "wc": rng.normal(0, small, (hidden, self.classes)).astype(F),
            "bc": np.log(mass / mass.sum()).astype(F),
            "ww": rng.normal(0, small, (self.head_classes, hidden, per_class)).astype(F),
            "bw": np.where(padded > 0, np.log(np.maximum(padded, 1e-9)), -30).reshape(-1, per_class).astype(F),
        }
        self.p["bw"] -= np.log(np.exp(self.p["bw"].astype(float)).sum(axis=1, keepdims=True)).astype(F)
        self.start, self._one = n, np.ones(1, F)

    # -- flat parameters ------------------------------------------------------------------------------
    def pack(self) -> np.ndarray:
        return np.concatenate([v.ravel() for v in self.p.values()])

    def unpack(self, flat: np.ndarray) -> "Gru":
        at = 0
        for k, v in self.p.items():
            self.p[k] = flat[at : at + v.size].reshape(v.shape).astype(F)
            at += v.size
        return self

    def class_of(self, ids: np.ndarray) -> np.ndarray:
        return np.where(ids < self.head, ids // self.per, self.head_classes + ids - self.head)

    # -- one window -----------------------------------------------------------------------------------
    def states(self, inputs: np.ndarray, fresh: np.ndarray, h: np.ndarray, keep: bool = False):
        """States after each of the (T, B) inputs, from h (B, H); where ``fresh`` the state is cleared first."""
        t_max, b = inputs.shape
        k = self.hidden
        # 1 / (1 + exp(-x)) for the gates, 2 / (1 + exp(-2 x)) - 1 for the candidate's tanh(x); gates and candidate apart, so that each is contiguous
        apart = lambda x, scale: np.ascontiguousarray((x * np.repeat(np.array(scale, F), [2 * k, k])).reshape(-1, 3, k).swapaxes(0, 1))
        gates, u = np.take(apart(self.p["g"], [-1, -2]), inputs, axis=1), apart(self.p["u"], [-1, 1])
        out = np.empty((t_max, b, k), F)
        kept = [np.empty((t_max, *n, b, k), F) for n in ((), (2,), (), ())] if keep else None  # state before, gates, candidate, its recurrent part
        cleared = fresh.any(axis=1)
        own = np.empty((2, b, k), F), np.empty((b, k), F)
        for t in range(t_max):
            if cleared[t]:
                h = np.where(fresh[t][:, None], F(0), h)
            hu = np.matmul(h, u)
            zr, n = (kept[1][t], kept[2][t]) if keep else own
            np.add(gates[:2, t], hu[:2], out=zr)
            np.minimum(zr, F(80), out=zr)
            np.exp(zr, out=zr)
            zr += F(1)
            np.reciprocal(zr, out=zr)
            np.multiply(zr[1], hu[2], out=n)
            n *= F(-2)
            n += gates[2, t]
            np.minimum(n, F(80), out=n)
            np.exp(n, out=n)
            n += F(1)
            np.divide(F(2), n, out=n)
            n -= F(1)
            if keep:
                kept[0][t], kept[3][t] = h, hu[2]
            new = out[t]
            np.subtract(h, n, out=new)
            new *= zr[0]
            new += n
            h = new
        return out, h, kept

    def log_probs(self, states: np.ndarray, targets: np.ndarray, grads: dict | None = None):
        """Natural log P of each target (N) from its state (N, H); with ``grads``, also the gradient to the states."""
        cls = self.class_of(targets)
        order = _order(cls, self.classes)  # all further work is in the order of classes, so that a class is a slice
        states, targets, cls = states[order], targets[order], cls[order]
        cut = np.searchsorted(cls, np.arange(self.head_classes + 1))
        n, rows, reach = len(targets), np.arange(len(targets)), max(float(states.max(initial=0)), -float(states.min(initial=0)))
        out, total = np.empty(n, states.dtype), np.empty(n, states.dtype)
        totals = np.ones_like(total)  # of the words in their classes; their logarithms are taken once
        wc, bc, ww, bw = (self.p[k] for k in ("wc", "bc", "ww", "bw"))
        back = None
        if grads is not None:
            back = np.empty_like(states)
            grads["wc"], grads["bc"] = np.zeros_like(wc), np.zeros_like(bc)
            grads["ww"], grads["bw"] = np.zeros_like(ww), np.zeros_like(bw)
        finite = _finite(reach, wc, bc)
        for a in range(0, n, ROWS):  # a piece of logits stays in the cache
            h, own = states[a : a + ROWS], rows[: min(ROWS, n - a)] * self.classes + cls[a : a + ROWS]
            out[a : a + ROWS], e, total[a : a + ROWS] = self._softmax(h @ wc, bc, own, finite)
            if grads is not None:
                e /= total[a : a + ROWS, None]
                e.reshape(-1)[own] -= 1
                grads["wc"] += h.T @ e
                grads["bc"] += self._ones(len(e)) @ e
                np.matmul(e, wc.T, out=back[a : a + ROWS])
        out -= np.log(total)
        known = int(cut[-1])
        used = np.flatnonzero(cut[1:] > cut[:-1])
        slices = [(c, int(cut[c]), int(cut[c + 1])) for c in used.tolist()]
        e = np.empty((known, self.per), states.dtype)
        for c, a, b in slices:  # only the products go class by class
            np.matmul(states[a:b], ww[c], out=e[a:b])
        own = rows[:known] * self.per + targets[:known] % self.per
        word, e, totals[:known] = self._softmax(e, bw[cls[:known]], own, _finite(reach, ww, bw))
        out[:known] += word
        if grads is not None and known:
            e /= totals[:known, None]
            e.reshape(-1)[own] -= 1
            grads["bw"][used] = np.add.reduceat(e, cut[used], axis=0)
            for c, a, b in slices:
                np.matmul(states[a:b].T, e[a:b], out=grads["ww"][c])
                back[a:b] += e[a:b] @ ww[c].T
        out -= np.log(totals)
        found = np.empty_like(out)
        found[order] = out
        if back is not None:
            plain = np.empty_like(back)
            plain[order] = back
            back = plain
        return found, back

    def _ones(self, n: int) -> np.ndarray:
        if len(self._one) < n:
            self._one = np.ones(n, F)
        return self._one[:n]

    def _softmax(self, e: np.ndarray, bias: np.ndarray, at: np.ndarray, finite: bool):
        """Of the logits ``e + bias`` (kept where their exponentials are finite, unless they are known to be): those at flat places ``at``, exponentials and their row sums."""
        e += bias
        if not finite:
            clip(e, F(-LOGITS), F(LOGITS), out=e)
        picked = e.reshape(-1)[at]
        np.exp(e, out=e)
        return picked, e, e @ self._ones(e.shape[1])

    def gradients(self, inputs: np.ndarray, targets: np.ndarray, mask: np.ndarray, fresh: np.ndarray, h: np.ndarray):
        """Mean loss, gradients by truncated backpropagation through the window, and the state after it."""
        t_max, b = inputs.shape
        k, ut = self.hidden, np.ascontiguousarray(self.p["u"].T)
        states, last, kept = self.states(inputs, fresh, h, keep=True)
        live = np.flatnonzero(mask.ravel())
        grads: dict[str, np.ndarray] = {}
        logp, back = self.log_probs(states.reshape(-1, k)[live], targets.ravel()[live], grads)
        dh_out = np.zeros((t_max * b, k), states.dtype)
        dh_out[live] = back
        dh_out = dh_out.reshape(t_max, b, k)
        before, zr, n, hn = kept
        z, r = zr[:, 0], zr[:, 1]
        # all factors that do not depend on the gradient, for the whole window at once
        to_n, to_z, to_r = (1 - z) * (1 - n * n), (before - n) * z * (1 - z), hn * r * (1 - r)
        da = np.empty((t_max, b, 3 * k), states.dtype)
        dhu = np.empty((t_max, b, 3 * k), states.dtype)
        dh = np.zeros((b, k), states.dtype)
        cleared = fresh.any(axis=1)
        for t in range(t_max - 1, -1, -1):
            dh += dh_out[t]
            dn = np.multiply(dh, to_n[t], out=da[t, :, 2 * k :])
            np.multiply(dh, to_z[t], out=da[t, :, :k])
            np.multiply(dn, to_r[t], out=da[t, :, k : 2 * k])
            dhu[t, :, : 2 * k] = da[t, :, : 2 * k]
            np.multiply(dn, r[t], out=dhu[t, :, 2 * k :])
            dh *= z[t]
            dh += dhu[t] @ ut
            if cleared[t]:
                dh[fresh[t]] = 0
        grads["u"] = before.reshape(-1, k).T @ dhu.reshape(-1, 3 * k)
        flat, da = inputs.ravel(), da.reshape(-1, 3 * k)
        order = _order(flat, self.start + 1)
        ids = flat[order]
        first = np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]]))
        ids = ids[first]
        grads["g"] = np.zeros_like(self.p["g"])
        grads["g"][ids] = np.add.reduceat(da[order], first, axis=0)
        count = max(1, len(live))
        for g in grads.values():
            g *= 1 / count
        return -float(logp.sum()) / count, grads, last

    # -- whole documents ------------------------------------------------------------------------------
    def score(self, ids: np.ndarray, offsets: np.ndarray, lanes: int = 256, window: int = 64) -> np.ndarray:
        """log10 P of every document, its state carried over all windows."""
        out = np.zeros(len(offsets) - 1)
        dealt, owner = Lanes(offsets, lanes), np.repeat(np.arange(len(out), dtype=np.int32), np.diff(offsets))
        h = np.zeros((dealt.n, self.hidden), F)
        for at, mask, fresh in dealt.windows(window):
            states, h, _ = self.states(self._inputs(ids, at, dealt.begins[at]), fresh, h[: at.shape[1]])
            live = np.flatnonzero(mask.ravel())
            at = at.ravel()[live]
            logp, _ = self.log_probs(states.reshape(-1, self.hidden)[live], ids[at])
            out += np.bincount(owner[at], weights=logp, minlength=len(out))
        return out / np.log(10)

    def _inputs(self, ids: np.ndarray, at: np.ndarray, begins: np.ndarray) -> np.ndarray:
        return np.where(begins, np.int32(self.start), ids[at - 1])

    def train(self, ids: np.ndarray, offsets: np.ndarray, lanes: int = 256, window: int = 16, rate: float = 0.03, segment: int = 512) -> "Gru":
        """One pass over the documents by Adam, a step for each window of truncated backpropagation, on fewer lanes where those would be less than STEPS. A long document is cut
        into segments, which go to lanes of their own; each starts from a cleared state, with the token before it as its first input."""
        lanes = max(LEAST_LANES, min(lanes, len(ids) // (window * STEPS)))
        rate *= np.sqrt(lanes / 256)
        dealt = Lanes(offsets, lanes, segment)
        h = np.zeros((dealt.n, self.hidden), F)
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        v2 = {k: np.zeros_like(v) for k, v in self.p.items()}
        steps = max(1, -(-dealt.longest // window))
        for i, (at, mask, fresh) in enumerate(dealt.windows(window)):
            _, grads, h = self.gradients(self._inputs(ids, at, dealt.begins[at]), ids[at], mask, fresh, h[: at.shape[1]])
            size = np.sqrt(sum(float(np.vdot(g, g)) for g in grads.values()))
            clip = min(1.0, 5.0 / (size + 1e-9))
            now = rate * (1 - 0.9 * i / steps) * np.sqrt(1 - 0.999 ** (i + 1)) / (1 - 0.9 ** (i + 1))
            for k, g in grads.items():
                for p, g, m1, m2 in _pieces(self.p[k], g, m[k], v2[k]):
                    g *= F(clip)
                    m1 *= F(0.9)
                    m1 += F(0.1) * g
                    g *= g
                    m2 *= F(0.999)
                    g *= F(0.001)
                    m2 += g
                    np.sqrt(m2, out=g)
                    g += F(1e-8)
                    np.divide(m1, g, out=g)
                    g *= F(now)
                    p -= g
        return self


def _order(keys: np.ndarray, count: int) -> np.ndarray:
    """The stable order of whole numbers from 0 to below ``count``; 16 bits are sorted by radix."""
    return np.argsort(keys.astype(np.uint16) if count <= 1 << 16 else keys, kind="stable")


def _finite(reach: float, w: np.ndarray, bias: np.ndarray) -> bool:
    """Whether no logit of states within ``reach`` can leave the bound, whatever the signs."""
    largest = lambda x: max(float(x.max(initial=0)), -float(x.min(initial=0)))
    return reach * w.shape[-2] * largest(w) + largest(bias) < LOGITS


def _pieces(*arrays: np.ndarray, size: int = 1 << 14):
    """The same flat pieces of arrays of one shape, as views that stay in the cache."""
    flat = [x.reshape(-1) for x in arrays]
    for a in range(0, len(flat[0]), size):
        yield [x[a : a + size] for x in flat]


class Lanes:
    """Documents (or segments of them) dealt to at most ``lanes`` lanes of about equal length, read window by window.

    What is held is the lanes' pieces, not an array as wide as all lanes and as long as the longest."""

    def __init__(self, offsets: np.ndarray, lanes: int, segment: int | None = None):
        starts, ends = offsets[:-1].astype(np.int64), offsets[1:].astype(np.int64)
        if segment:
            parts = np.maximum(1, -(-(ends - starts) // segment))
            base = np.repeat(starts, parts)
            no = np.arange(len(base)) - np.repeat(np.cumsum(parts) - parts, parts)
            ends = np.minimum(base + (no + 1) * segment, np.repeat(ends, parts))
            starts = base + no * segment
        lengths = ends - starts
        self.begins = np.zeros(int(offsets[-1]) + 1, bool)
        self.begins[offsets[:-1]] = True
        heap = [(0, i) for i in range(max(1, min(lanes, len(lengths))))]
        dealt: list[list[int]] = [[] for _ in heap]
        for d in np.argsort(-lengths, kind="stable").tolist():
            size, i = heapq.heappop(heap)
            dealt[i].append(d)
            heapq.heappush(heap, (size + int(lengths[d]), i))
        sizes = {i: s for s, i in heap}
        order = sorted(range(len(dealt)), key=lambda i: -sizes[i])
        self.n, self.sizes = len(order), np.array([sizes[i] for i in order])
        self.longest = int(self.sizes[0])
        pieces = np.array([d for i in order for d in dealt[i]], np.int64)
        #: one lane after another: the place of each token, and whether a piece begins there
        cut = np.concatenate([[0], np.cumsum(lengths[pieces])]) if len(pieces) else np.zeros(1, np.int64)
        self.places = np.arange(cut[-1], dtype=np.int32 if offsets[-1] < 1 << 31 else np.int64)
        self.places += np.repeat(starts[pieces] - cut[:-1], lengths[pieces]).astype(self.places.dtype)
        self.heads = np.zeros(len(self.places), bool)
        self.heads[cut[:-1][lengths[pieces] > 0]] = True
        self.base = np.concatenate([[0], np.cumsum(self.sizes)])[:-1]

    def windows(self, window: int):
        """(places of tokens, which of them count, which begin a piece), each (steps, lanes alive)."""
        for t in range(0, self.longest, window):
            b = int(np.searchsorted(-self.sizes, -t, side="left"))
            at = self.base[:b] + np.arange(t, min(t + window, self.longest))[:, None]
            mask = np.arange(t, min(t + window, self.longest))[:, None] < self.sizes[:b]
            at = np.where(mask, at, self.base[:b] + t)  # padding repeats the first place
            yield self.places[at], mask, mask & self.heads[at]
