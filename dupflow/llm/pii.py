"""Personal data: fixed patterns, and a character-level bidirectional LSTM with CRF transitions.

The network is trained here in numpy from labelled spans.  A text is decoded in
overlapping windows around its anchors, characters that every kind of personal
data here must hold; the windows' scores are blended by how central a character
is in each, and one Viterbi pass over the whole stretch gives the spans.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dupflow.llm.common import text_or_empty

#: Kinds in their order.
KINDS = ["email", "ip", "card", "phone"]
LABELS = 1 + 2 * len(KINDS)
WINDOW, STRIDE, MARGIN = 64, 32, 24
CHARS = 131

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])([0-9]+)\.([0-9]+)\.([0-9]+)\.([0-9]+)")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")
_ANCHOR = re.compile(r"[0-9@]")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        x = int(d) * (1 + i % 2)
        total += x - 9 if x > 9 else x
    return total % 10 == 0


def emails(t: str) -> Iterator[tuple[int, int]]:
    """Leftmost matches, found from each at sign outwards."""
    free, at = 0, t.find("@")
    while at >= 0:
        lo = at
        while lo > free and t[lo - 1] in _LOCAL:
            lo -= 1
        m = _DOMAIN.match(t, at + 1) if lo < at else None
        if m:
            yield lo, m.end()
            free = m.end()
        at = t.find("@", max(at + 1, free))


def base_spans(t: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the fixed patterns, leftmost non-overlapping for each kind."""
    out = [(a, 0, b) for a, b in emails(t)] if "@" in t else []
    if not _DIGIT.search(t):
        return out
    out += [(m.start(), 1, m.end()) for m in _IP.finditer(t) if all(len(p.lstrip("0")) < 4 and int(p.lstrip("0") or 0) < 256 for p in m.groups())]
    for m in _CARD.finditer(t):
        digits = m[0].replace(" ", "").replace("-", "")
        if 14 <= len(digits) <= 19 and luhn(digits):
            out.append((m.start(), 2, m.end()))
    if "+" in t:
        out += [(m.start(), 3, m.end()) for m in _PHONE.finditer(t) if 10 <= sum("0" <= c <= "9" for c in m[0]) <= 15]
    return sorted(out)


def char_ids(t: str) -> np.ndarray:
    """Numbers of characters: ASCII as it is, other letters 128, all else 129; 130 pads."""
    c = np.frombuffer(t.encode("utf-32-le"), "<u4").astype(np.int64)
    far = np.nonzero(c > 127)[0]
    for i in far:
        c[i] = 128 if t[i].isalpha() else 129
    return c


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Tagger:
    """Embedding, two LSTM directions, linear emissions and CRF transitions."""

    def __init__(self, embed: int = 12, hidden: int = 20, seed: int = 7):
        r = np.random.default_rng(seed)
        self.h = hidden
        init = lambda *s: (r.standard_normal(s) / np.sqrt(s[0])).astype(np.float32)
        self.p = {"E": init(CHARS, embed) * 3, "Wo": init(2 * hidden, LABELS), "bo": np.zeros(LABELS, np.float32), "T": np.zeros((LABELS, LABELS), np.float32)}
        for d in "fb":
            self.p |= {f"W{d}": init(embed, 4 * hidden), f"U{d}": init(hidden, 4 * hidden), f"b{d}": np.zeros(4 * hidden, np.float32)}
            self.p[f"b{d}"][hidden : 2 * hidden] = 1
        self.block = np.zeros((LABELS, LABELS), np.float32)
        for j in range(2, LABELS, 2):  # inside labels follow only their own kind
            for i in range(LABELS):
                if i not in (j, j - 1):
                    self.block[i, j] = -1e4
        self.start = np.array([0 if j % 2 or j == 0 else -1e4 for j in range(LABELS)], np.float32)

    def _run(self, x, d, keep: bool):
        """x: time, batch, embed; hidden states in time order of the direction."""
        h, n = self.h, x.shape[1]
        pre = x @ self.p[f"W{d}"] + self.p[f"b{d}"]
        u, hs, cs = self.p[f"U{d}"], np.zeros((len(x) + 1, n, h), np.float32), np.zeros((len(x) + 1, n, h), np.float32)
        gates = np.empty((len(x), n, 4 * h), np.float32) if keep else None
        for t in range(len(x)):
            z = pre[t] + hs[t] @ u
            z[:, : 3 * h] = 0.5 * (1 + np.tanh(0.5 * z[:, : 3 * h]))
            z[:, 3 * h :] = np.tanh(z[:, 3 * h :])
            cs[t + 1] = z[:, h : 2 * h] * cs[t] + z[:, :h] * z[:, 3 * h :]
            hs[t + 1] = z[:, 2 * h : 3 * h] * np.tanh(cs[t + 1])
            if keep:
                gates[t] = z
        return hs, cs, gates

    def emissions(self, ids: np.ndarray) -> np.ndarray:
        """Scores (batch, time, label) of windows of character numbers."""
        x = self.p["E"][ids.T]
        f = self._run(x, "f", False)[0][1:]
        b = self._run(x[::-1], "b", False)[0][1:][::-1]
        return (np.concatenate([f, b], 2) @ self.p["Wo"] + self.p["bo"]).transpose(1, 0, 2)

    def _back(self, x, d, state, dh_out):
        """Gradients of one direction for the hidden states' gradient."""
        h, (hs, cs, g) = self.h, state
        u, dh, dc = self.p[f"U{d}"], 0.0, 0.0
        dz = np.empty_like(g)
        for t in range(len(x) - 1, -1, -1):
            i, f, o, c = g[t, :, :h], g[t, :, h : 2 * h], g[t, :, 2 * h : 3 * h], g[t, :, 3 * h :]
            dh = dh + dh_out[t]
            tc = np.tanh(cs[t + 1])
            dc = dc + dh * o * (1 - tc * tc)
            dz[t, :, :h] = dc * c * i * (1 - i)
            dz[t, :, h : 2 * h] = dc * cs[t] * f * (1 - f)
            dz[t, :, 2 * h : 3 * h] = dh * tc * o * (1 - o)
            dz[t, :, 3 * h :] = dc * i * (1 - c * c)
            dh, dc = dz[t] @ u.T, dc * f
        flat = dz.reshape(-1, 4 * h)
        return {f"W{d}": x.reshape(-1, x.shape[2]).T @ flat, f"U{d}": hs[:-1].reshape(-1, h).T @ flat, f"b{d}": flat.sum(0)}, dz @ self.p[f"W{d}"].T

    def _crf(self, e, gold):
        """Negative log likelihood and its gradients; e: batch, time, label."""
        n, steps, _ = e.shape
        trans = self.p["T"] + self.block
        a = np.empty_like(e)
        a[:, 0] = e[:, 0] + self.start
        lse = lambda x, ax: (m := x.max(ax, keepdims=True)).squeeze(ax) + np.log(np.exp(x - m).sum(ax))
        for t in range(1, steps):
            a[:, t] = e[:, t] + lse(a[:, t - 1, :, None] + trans, 1)
        z = lse(a[:, -1], 1)
        b = np.zeros_like(e)
        for t in range(steps - 2, -1, -1):
            b[:, t] = lse(trans + (e[:, t + 1] + b[:, t + 1])[:, None, :], 2)
        marg = np.exp(a + b - z[:, None, None])
        pair = np.exp(a[:, :-1, :, None] + trans + (e[:, 1:] + b[:, 1:])[:, :, None, :] - z[:, None, None, None])
        rows, cols = np.arange(n)[:, None], np.arange(steps)
        score = e[rows, cols, gold].sum(1) + trans[gold[:, :-1], gold[:, 1:]].sum(1)
        marg[rows, cols, gold] -= 1
        dt = pair.sum((0, 1))
        np.subtract.at(dt, (gold[:, :-1], gold[:, 1:]), 1)
        return float((z - score).mean()), marg / n, dt / n

    def train(self, ids: np.ndarray, gold: np.ndarray, epochs: int = 6, batch: int = 64, rate: float = 0.01, seed: int = 7) -> list[float]:
        """Adam over labelled windows; returns the mean loss of each epoch."""
        r = np.random.default_rng(seed)
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        v = {k: np.zeros_like(x) for k, x in self.p.items()}
        step, losses = 0, []
        for epoch in range(epochs):
            order, total = r.permutation(len(ids)), []
            for lo in range(0, len(ids), batch):
                pick = order[lo : lo + batch]
                x = self.p["E"][ids[pick].T]
                fs, bs = self._run(x, "f", True), self._run(x[::-1], "b", True)
                hidden = np.concatenate([fs[0][1:], bs[0][1:][::-1]], 2)
                e = (hidden @ self.p["Wo"] + self.p["bo"]).transpose(1, 0, 2)
                loss, de, dt = self._crf(e.astype(np.float64), gold[pick])
                de = de.transpose(1, 0, 2).astype(np.float32)
                dh = de @ self.p["Wo"].T
                g = {"Wo": hidden.reshape(-1, 2 * self.h).T @ de.reshape(-1, LABELS), "bo": de.sum((0, 1)), "T": dt.astype(np.float32)}
                gf, dxf = self._back(x, "f", fs, dh[:, :, : self.h])
                gb, dxb = self._back(x[::-1], "b", bs, dh[::-1, :, self.h :])
                g |= gf | gb
                g["E"] = np.zeros_like(self.p["E"])
                np.add.at(g["E"], ids[pick].T, dxf + dxb[::-1])
                step += 1
                size = np.sqrt(sum(float((x * x).sum()) for x in g.values()))
                for k in self.p:
                    gk = g[k] * min(1, 5 / (size + 1e-9))
                    m[k] = 0.9 * m[k] + 0.1 * gk
                    v[k] = 0.99 * v[k] + 0.01 * gk * gk
                    self.p[k] -= rate * (0.5 ** (epoch / 3)) * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)
                total.append(loss)
            losses.append(float(np.mean(total)))
        return losses

    def viterbi(self, e: np.ndarray, lengths: np.ndarray) -> list[np.ndarray]:
        """Best label path of each padded row of scores (row, time, label)."""
        n, steps, _ = e.shape
        trans = self.p["T"] + self.block
        best = e[:, 0] + self.start
        back = np.zeros((n, steps, LABELS), np.int8)
        rest = np.arange(LABELS)
        for t in range(1, steps):
            options = best[:, :, None] + trans
            back[:, t] = options.argmax(1)
            moved = options.max(1) + e[:, t]
            over = t >= lengths
            back[over, t] = rest
            best = np.where(over[:, None], best, moved)
        path = np.zeros((n, steps), np.int8)
        path[:, -1] = best.argmax(1)
        for t in range(steps - 1, 0, -1):
            path[:, t - 1] = back[np.arange(n), t, path[:, t]]
        return [path[i, :k] for i, k in enumerate(lengths)]


def stretches(t: str) -> list[tuple[int, int]]:
    """The parts of a text within a margin of an anchor, merged where they meet.

    No kind of personal data here is without an anchor, so all other
    characters are outside by the model's own constraint.
    """
    out: list[list[int]] = []
    for m in _ANCHOR.finditer(t):
        lo, hi = max(0, m.start() - MARGIN), min(len(t), m.end() + MARGIN)
        if out and lo <= out[-1][1]:
            out[-1][1] = hi
        else:
            out.append([lo, hi])
    return [(a, b) for a, b in out]


def path_spans(path: np.ndarray, base: int) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of a label path."""
    out, open_at, kind = [], -1, -1
    for i, label in enumerate([*path.tolist(), 0]):
        if open_at >= 0 and (label == 0 or label % 2):
            out.append((base + open_at, kind, base + i))
            open_at = -1
        if label % 2:
            open_at, kind = i, (label - 1) // 2
    return out


def decode(model: Tagger, texts: list[str], block: int = 512) -> list[list[tuple[int, int, int]]]:
    """Model spans of each whole text: windows scored in blocks, blended, one Viterbi for each stretch.

    A span must hold its kind's anchor: an at sign for an address, else a digit.
    """
    parts = [(d, a, b) for d, t in enumerate(texts) for a, b in stretches(t)]
    out: list[list[tuple[int, int, int]]] = [[] for _ in texts]
    parts.sort(key=lambda x: x[2] - x[1])
    at = 0
    while at < len(parts):
        hi, size = at, 0
        while hi < len(parts) and hi - at < block and (hi == at or size + parts[hi][2] - parts[hi][1] < 200_000):
            size += parts[hi][2] - parts[hi][1]
            hi += 1
        some = parts[at:hi]
        lengths = np.array([b - a for _, a, b in some])
        scores = np.zeros((len(some), int(lengths.max()), LABELS), np.float32)
        weights = np.zeros(scores.shape[:2], np.float32)
        wins, where = [], []
        for i, (d, a, b) in enumerate(some):
            ids = char_ids(texts[d][a:b])
            for lo in range(0, max(1, len(ids) - WINDOW + STRIDE), STRIDE):
                w = ids[lo : lo + WINDOW]
                wins.append(np.pad(w, (0, WINDOW - len(w)), constant_values=130))
                where.append((i, lo, len(w)))
        for lo in range(0, len(wins), 2048):
            e = model.emissions(np.stack(wins[lo : lo + 2048]))
            for (i, s, n), x in zip(where[lo : lo + 2048], e, strict=True):
                w = np.minimum(np.arange(1, n + 1), np.arange(n, 0, -1)).astype(np.float32)
                scores[i, s : s + n] += w[:, None] * x[:n]
                weights[i, s : s + n] += w
        scores /= np.maximum(weights, 1)[:, :, None]
        for (d, a, _), path in zip(some, model.viterbi(scores, lengths), strict=True):
            t = texts[d]
            out[d] += [(lo, k, hi) for lo, k, hi in path_spans(path, a) if ("@" in t[lo:hi] if k == 0 else _DIGIT.search(t, lo, hi))]
        at = hi
    return out


def labelled_examples(n: int, seed: int = 11) -> tuple[list[str], list[list[tuple[int, int, int]]]]:
    """Made-up texts with labelled spans of public formats, and number-like distractors without labels."""
    r = np.random.default_rng(seed)
    pick = lambda xs: xs[int(r.integers(len(xs)))]
    digits = lambda k: "".join(map(str, r.integers(0, 10, k)))
    letters = "aaabcdeeeefghiiijklmnnnoooprrsssttttuvwxyzéèüöñ"
    word = lambda: "".join(pick(letters) for _ in range(int(r.integers(2, 9))))
    hexes = lambda k: "".join(pick("0123456789abcdef") for _ in range(k))

    def email():
        local = pick([word(), f"{word()}.{digits(2)}", f"{word()}_{word()}", f"{word()}+{digits(1)}"])
        return f"{local}{pick(['@', '@', '@', ' @ '])}{pick([f'mail{digits(1)}.example.com', f'{word()}.org', f'{word()}.co.uk', f'{word()}-{word()}.net'])}".replace("é", "e").replace("è", "e").replace("ü", "u").replace("ö", "o").replace("ñ", "n")

    def ip():
        return ".".join(str(x) for x in r.integers(0, 256, 4))

    def card():
        d = digits(int(pick([14, 15, 16, 16, 16, 16, 19])))
        return pick([d, d, d, " ".join(d[i : i + 4] for i in range(0, len(d), 4)), "-".join(d[i : i + 4] for i in range(0, len(d), 4))])

    def phone():
        a, b, c = digits(3), digits(3), digits(4)
        return pick([f"+{pick('1234')} ({a}) {b}-{c}", f"+{digits(2)} {a} {b} {c}", f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"+{digits(2)}{a}{b}{c}", f"{a}.{b}.{c}", f"+1 {a}-{b}-{c}"])

    def other():
        return pick([f'token = "{hexes(40)}"', f"version {digits(1)}.{digits(1)}.", f"CC BY-NC {digits(1)}.{digits(1)}.", digits(int(r.integers(1, 7))), f"{digits(4)}-{digits(2)}-{digits(2)}", f"${digits(2)}.{digits(2)}", f"{digits(2)}:{digits(2)}", f"{digits(2)}%", f"{digits(1)},{digits(3)}", f"@{word()}", hexes(32), f"v{digits(1)}.{digits(1)}.{digits(1)}", f"AKIA{digits(4)}XYZQ{digits(8)}"])

    texts, spans = [], []
    for _ in range(n):
        t, s = "", []
        glue = lambda: pick([" ", " ", " ", " ", "\n", ", ", ". ", "### ", "!! ", " | ", ": ", "*** "])
        while len(t) < WINDOW + 16:
            x = r.random()
            if x < 0.62:
                t += (word().upper() if r.random() < 0.1 else word()) + glue()
            elif x < 0.78:
                t += other() + glue()
            else:
                k = int(r.integers(4))
                v = (email, ip, card, phone)[k]()
                v = v.upper() if r.random() < 0.05 else v
                s.append((len(t), k, len(t) + len(v)))
                t += v + glue()
        texts.append(t)
        spans.append(s)
    return texts, spans


def labelled_windows(texts: list[str], spans: list[list[tuple[int, int, int]]], seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Windows of character numbers and labels, from random places of labelled texts; some are padded."""
    r = np.random.default_rng(seed)
    ids, gold = np.full((len(texts), WINDOW), 130), np.zeros((len(texts), WINDOW), np.int64)
    for i, (t, ss) in enumerate(zip(texts, spans, strict=True)):
        lab = np.zeros(len(t), np.int64)
        for a, k, b in ss:
            lab[a:b] = 2 + 2 * k
            lab[a] = 1 + 2 * k
        lo = int(r.integers(0, max(1, len(t) - WINDOW + 1)))
        n = WINDOW if r.random() < 0.8 else int(r.integers(16, WINDOW))
        n = min(n, len(t) - lo)
        ids[i, :n], gold[i, :n] = char_ids(t)[lo : lo + n], lab[lo : lo + n]
        if gold[i, 0] and gold[i, 0] % 2 == 0:  # the window begins inside a span
            gold[i, 0] -= 1
    return ids, gold


_MODELS: dict[tuple, Tagger] = {}


def trained(examples: int = 3200, epochs: int = 7, seed: int = 7) -> Tagger:
    """The tagger after training on ``examples`` made-up labelled texts; once for each process and setting."""
    key = (examples, epochs, seed)
    if key not in _MODELS:
        model = Tagger(seed=seed)
        model.train(*labelled_windows(*labelled_examples(examples)), epochs=epochs)
        _MODELS[key] = model
    return _MODELS[key]


def written(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in sorted(spans))


def all_spans(model: Tagger, texts: list[str]) -> list[tuple[list, list]]:
    """(base spans, all spans) of each text: the model adds those that meet no base span."""
    found = []
    for t, extra in zip(texts, decode(model, texts), strict=True):
        base = base_spans(t)
        found.append((base, base + [(a, k, b) for a, k, b in extra if not any(x < b and a < y for x, _, y in base)]))
    return found


FOUND = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"


def find_personal_data(docs: DataFrame, model: Tagger | None = None) -> DataFrame:
    """One row for each document: base counts and digest, and all spans.

    Null texts are empty; rows with null or repeated ids stay rows of their
    own; other columns are not read; an empty table gives no rows.
    """
    model = model or trained()
    schema = pa.schema([("doc_id", pa.int64()), *[(f"n_{k}", pa.int64()) for k in KINDS], ("base_sha256", pa.string()), ("spans", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).to_pylist()
            cols: list[list] = [[] for _ in range(6)]
            for lo in range(0, len(texts), 512):
                for base, every in all_spans(model, texts[lo : lo + 512]):
                    kinds = [k for _, k, _ in base]
                    for k in range(4):
                        cols[k].append(kinds.count(k))
                    cols[4].append(hashlib.sha256(written(base).encode()).hexdigest())
                    cols[5].append(written(every))
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, f.type) for c, f in zip(cols, list(schema)[1:], strict=True)]], schema=schema)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")).mapInArrow(run, FOUND)
