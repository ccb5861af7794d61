"""Personal data: a character-level bidirectional LSTM with CRF transitions, in NumPy.

The model reads character classes and labels every character with O or with B or I of a kind. It is
trained on the driver from labelled spans (by default a seeded generator of examples and look-alikes;
any list of texts with spans will do). Texts are covered by overlapping windows; every window decides
the characters in its middle, and the decisions are joined over the whole text before spans are read
off, so a span may cross windows.

A span counts only if it holds a digit or an at sign. That makes a window without either yield
nothing whatever the model says, so such windows need no evaluation: this changes no result.

Exact patterns give the base spans; spans of the model are added where they touch no base span.

Defined results: null text is empty text; every input row gives one output row; no finds give counts
of 0, the digest of the empty string and an empty list; an empty table gives an empty result; further
columns are ignored. Offsets are code points, end exclusive.
"""

from __future__ import annotations

import hashlib
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.llm.common import ship

KINDS = ("email", "ip", "card", "phone")
HIDDEN, EMBED = 16, 10
WINDOW, STRIDE = 96, 64
MARGIN = (WINDOW - STRIDE) // 2
LABELS = 1 + 2 * len(KINDS)

# ---------------------------------------------------------------- exact patterns

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9]){12,}+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_TRIGGER = re.compile(r"[0-9@]")


def _emails(text: str):
    free, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL:
            start -= 1
        domain = _DOMAIN.match(text, at + 1) if start < at else None
        if domain:
            yield start, domain.end()
            free = domain.end()
        at = text.find("@", max(at + 1, free))


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind, start, end) of the exact patterns, by kind, then start."""
    found = [(0, a, b) for a, b in _emails(text)]
    if not re.search("[0-9]", text):
        return found
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p[-4:]) <= 255 for p in m[0].split(".")):
            found.append((1, *m.span()))
    for m in _CARD.finditer(text):
        digits = re.sub("[ -]", "", m[0])
        if 13 <= len(digits) <= 19 and luhn(digits):
            found.append((2, *m.span()))
    for m in _PHONE.finditer(text):
        if 9 <= sum(c.isdigit() for c in m[0]) <= 15:
            found.append((3, *m.span()))
    return found


# ---------------------------------------------------------------- characters

_PUNCTUATION = "@.+-() \n:/_%,;'\"=#&*"
N_CLASSES = 6 + len(_PUNCTUATION)
_CLASS = np.full(129, 5, np.int64)
for _i in range(128):
    _c = chr(_i)
    _CLASS[_i] = 6 + _PUNCTUATION.index(_c) if _c in _PUNCTUATION else 1 if _c.isdigit() else 2 if _c in "abcdef" else 3 if _c.islower() else 4 if _c.isupper() else 5
_CLASS[128] = 3  # letters beyond ASCII, as lower-case ones
PAD = 0


def classes(text: str) -> np.ndarray:
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    return _CLASS[np.minimum(points, 128)]


# ---------------------------------------------------------------- the model


def _sigmoid(x):
    return 0.5 * (1.0 + np.tanh(0.5 * x))


class Tagger:
    """Embedding, one LSTM in each direction, a linear layer and a linear-chain CRF."""

    def __init__(self, seed: int = 5):
        rng = np.random.default_rng(seed)
        normal = lambda *s: (rng.normal(size=s) * 0.15).astype(np.float32)
        self.p = {"emb": normal(N_CLASSES, EMBED), "out": normal(2 * HIDDEN, LABELS), "bias": np.zeros(LABELS, np.float32), "trans": normal(LABELS, LABELS)}
        for d in "fb":
            self.p |= {f"x{d}": normal(EMBED, 4 * HIDDEN), f"h{d}": normal(HIDDEN, 4 * HIDDEN), f"c{d}": np.zeros(4 * HIDDEN, np.float32)}
            self.p[f"c{d}"][HIDDEN : 2 * HIDDEN] = 1.0

    def _lstm(self, x: np.ndarray, d: str, keep: bool):
        """x (T, N, EMBED) -> states (T, N, HIDDEN) in reading order of direction d."""
        steps, n, _ = x.shape
        gates_x = x @ self.p[f"x{d}"] + self.p[f"c{d}"]
        h = np.zeros((n, HIDDEN), np.float32)
        c = np.zeros((n, HIDDEN), np.float32)
        states, tape = np.empty((steps, n, HIDDEN), np.float32), []
        for t in range(steps):
            g = gates_x[t] + h @ self.p[f"h{d}"]
            s = _sigmoid(g[:, : 3 * HIDDEN])
            i, f, o, u = s[:, :HIDDEN], s[:, HIDDEN : 2 * HIDDEN], s[:, 2 * HIDDEN :], np.tanh(g[:, 3 * HIDDEN :])
            before, last = c, h
            c = f * c + i * u
            tc = np.tanh(c)
            h = o * tc
            states[t] = h
            if keep:
                tape.append((i, f, o, u, before, tc, last))
        return states, tape

    def scores(self, ids: np.ndarray, keep: bool = False):
        """ids (N, T) -> label scores (T, N, LABELS)."""
        x = self.p["emb"][ids.T]
        forward, tape_f = self._lstm(x, "f", keep)
        backward, tape_b = self._lstm(x[::-1], "b", keep)
        both = np.concatenate([forward, backward[::-1]], axis=2)
        return both @ self.p["out"] + self.p["bias"], (x, both, tape_f, tape_b)

    def decode(self, ids: np.ndarray) -> np.ndarray:
        """The best label sequence of every window, (N, T)."""
        emit, _ = self.scores(ids)
        steps, n, _ = emit.shape
        best, back = emit[0], np.empty((steps, n, LABELS), np.int8)
        for t in range(1, steps):
            all_ = best[:, :, None] + self.p["trans"]
            back[t] = all_.argmax(1)
            best = all_.max(1) + emit[t]
        out = np.empty((steps, n), np.int64)
        out[-1] = best.argmax(1)
        for t in range(steps - 1, 0, -1):
            out[t - 1] = back[t][np.arange(n), out[t]]
        return out.T

    def _crf(self, emit: np.ndarray, gold: np.ndarray):
        """Loss and its gradients by emission and transition; gold (T, N)."""
        steps, n, _ = emit.shape
        trans = self.p["trans"]

        def logsum(a, axis):
            m = a.max(axis, keepdims=True)
            return np.squeeze(m, axis) + np.log(np.exp(a - m).sum(axis))

        alpha, beta = np.empty_like(emit), np.zeros_like(emit)
        alpha[0] = emit[0]
        for t in range(1, steps):
            alpha[t] = logsum(alpha[t - 1][:, :, None] + trans, 1) + emit[t]
        for t in range(steps - 2, -1, -1):
            beta[t] = logsum(trans + (emit[t + 1] + beta[t + 1])[:, None, :], 2)
        z = logsum(alpha[-1], 1)
        d_emit = np.exp(alpha + beta - z[None, :, None])
        d_trans = np.zeros_like(trans)
        for t in range(1, steps):
            d_trans += np.exp(alpha[t - 1][:, :, None] + trans + (emit[t] + beta[t])[:, None, :] - z[:, None, None]).sum(0)
        rows = np.arange(n)
        score = np.zeros(n)
        for t in range(steps):
            score += emit[t, rows, gold[t]] + (trans[gold[t - 1], gold[t]] if t else 0)
            d_emit[t, rows, gold[t]] -= 1
            if t:
                np.add.at(d_trans, (gold[t - 1], gold[t]), -1)
        return float((z - score).mean()), d_emit / n, d_trans / n

    def _lstm_back(self, x, d: str, d_states, tape, grads):
        dh = np.zeros_like(d_states[0])
        dc = np.zeros_like(dh)
        d_gates = np.empty((*d_states.shape[:2], 4 * HIDDEN), np.float32)
        for t in range(len(tape) - 1, -1, -1):
            i, f, o, u, before, tc, last = tape[t]
            dh = dh + d_states[t]
            dc = dc + dh * o * (1 - tc * tc)
            g = d_gates[t]
            g[:, :HIDDEN] = dc * u * i * (1 - i)
            g[:, HIDDEN : 2 * HIDDEN] = dc * before * f * (1 - f)
            g[:, 2 * HIDDEN : 3 * HIDDEN] = dh * tc * o * (1 - o)
            g[:, 3 * HIDDEN :] = dc * i * (1 - u * u)
            grads[f"h{d}"] += last.T @ g
            dc = dc * f
            dh = g @ self.p[f"h{d}"].T
        grads[f"x{d}"] += np.einsum("tne,tng->eg", x, d_gates, optimize=True)
        grads[f"c{d}"] += d_gates.sum((0, 1))
        return d_gates @ self.p[f"x{d}"].T

    def step(self, ids: np.ndarray, gold: np.ndarray) -> tuple[float, dict]:
        emit, (x, both, tape_f, tape_b) = self.scores(ids, True)
        loss, d_emit, d_trans = self._crf(emit.astype(np.float64), gold.T)
        d_emit = d_emit.astype(np.float32)
        grads = {k: np.zeros_like(v) for k, v in self.p.items()}
        grads["trans"] = d_trans.astype(np.float32)
        grads["out"] = np.einsum("tnh,tnl->hl", both, d_emit, optimize=True)
        grads["bias"] = d_emit.sum((0, 1))
        d_both = d_emit @ self.p["out"].T
        dx = self._lstm_back(x, "f", d_both[:, :, :HIDDEN], tape_f, grads)
        dx += self._lstm_back(x[::-1], "b", d_both[::-1, :, HIDDEN:], tape_b, grads)[::-1]
        np.add.at(grads["emb"], ids.T, dx)
        return loss, grads

    def fit(self, ids: np.ndarray, gold: np.ndarray, steps: int, batch: int = 48, rate: float = 0.02, seed: int = 3) -> list[float]:
        """Adam on random batches of windows; the losses."""
        rng, losses = np.random.default_rng(seed), []
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        v = {k: np.zeros_like(x) for k, x in self.p.items()}
        for t in range(1, steps + 1):
            rows = rng.integers(0, len(ids), batch)
            loss, grads = self.step(ids[rows], gold[rows])
            losses.append(loss)
            now = rate * (1 - 0.9 * t / steps)
            for k, g in grads.items():
                g = np.clip(g, -1, 1)
                m[k] += 0.1 * (g - m[k])
                v[k] += 0.01 * (g * g - v[k])
                self.p[k] -= now * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.99**t)) + 1e-6)
        return losses


# ---------------------------------------------------------------- labelled examples


def examples(n: int, seed: int = 1) -> list[tuple[str, list[tuple[int, int, int]]]]:
    """Seeded texts with labelled spans (kind, start, end), look-alikes among them unlabelled."""
    rng = np.random.default_rng(seed)
    letters = np.array(list("abcdefghijklmnopqrstuvwxyzéèñü"))
    pick = lambda x: x[int(rng.integers(len(x)))]
    digits = lambda k: "".join(map(str, rng.integers(0, 10, k)))
    word = lambda a, b: "".join(rng.choice(letters, int(rng.integers(a, b))))
    plain = lambda a, b: "".join(rng.choice(letters[:26], int(rng.integers(a, b))))

    def card() -> str:
        body = pick("3456") + digits(14)
        last = next(d for d in "0123456789" if luhn(body + d))
        number = body + last
        sep = pick(["", "", " ", "-"])
        return sep.join(number[i : i + 4] for i in range(0, 16, 4))

    def phone() -> str:
        a, b, c = digits(3), digits(3), digits(4)
        return pick([f"+1 ({a}) {b}-{c}", f"+{digits(2)} {a} {b} {c}", f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"+{digits(1)}-{a}-{b}-{c}", f"{a}.{b}.{c}"])

    make = (
        lambda: f"{plain(2, 9)}{pick(['.', '_', ''])}{digits(int(rng.integers(0, 3)))}@{plain(3, 9)}{digits(int(rng.integers(0, 2)))}.{pick(['example.com', 'com', 'org', 'co.uk', 'net'])}",
        lambda: ".".join(str(x) for x in rng.integers(0, 256, 4)),
        card,
        phone,
    )
    decoys = (
        lambda: "".join(rng.choice(list("0123456789abcdef"), int(rng.integers(16, 41)))),
        lambda: f"{rng.integers(1, 29)}.{rng.integers(1, 13)}.{rng.integers(1900, 2030)}",
        lambda: f"{rng.integers(1900, 2030)}-{rng.integers(10, 13)}-{rng.integers(10, 29)}",
        lambda: f"{digits(int(rng.integers(1, 7)))}",
        lambda: f"${rng.integers(1, 999)},{digits(3)}.{digits(2)}",
        lambda: f"v{rng.integers(0, 9)}.{rng.integers(0, 30)}.{rng.integers(0, 9)}",
        lambda: f"AKIA{''.join(rng.choice(list('ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789'), 16))}",
        lambda: f"password={''.join(rng.choice(list('0123456789abcdef'), 16))}",
        lambda: f"@{plain(3, 9)}",
        lambda: f"{rng.integers(0, 23)}:{rng.integers(10, 59)}",
    )
    out = []
    for _ in range(n):
        text, spans = "", []
        while len(text) < WINDOW:
            if rng.random() < 0.35:
                kind = int(rng.integers(len(KINDS)))
                piece = make[kind]()
                spans.append((kind, len(text), len(text) + len(piece)))
            elif rng.random() < 0.3:
                piece = pick(decoys)()
            else:
                piece = word(1, 10)
            text += piece + pick([" ", " ", " ", " ", ", ", ". ", "\n"])
        out.append((text, spans))
    return out


def windows_of(samples) -> tuple[np.ndarray, np.ndarray]:
    """Character classes and labels of the first window of each sample."""
    ids = np.full((len(samples), WINDOW), PAD, np.int64)
    gold = np.zeros((len(samples), WINDOW), np.int64)
    for r, (text, spans) in enumerate(samples):
        c = classes(text[:WINDOW])
        ids[r, : len(c)] = c
        for kind, a, b in spans:
            if a < WINDOW:
                gold[r, a] = 1 + 2 * kind
                gold[r, a + 1 : min(b, WINDOW)] = 2 + 2 * kind
    return ids, gold


@lru_cache(maxsize=2)
def trained(n: int = 3000, steps: int = 350, seed: int = 5) -> Tagger:
    tagger = Tagger(seed)
    tagger.fit(*windows_of(examples(n, seed)), steps)
    return tagger


# ---------------------------------------------------------------- whole texts


def model_spans(texts: list[str], tagger: Tagger, most: int = 256) -> list[list[tuple[int, int, int]]]:
    """(kind, start, end) that the model finds in each text."""
    jobs = []
    for i, text in enumerate(texts):
        # windows that hold a digit or an at sign; window w decides [w * STRIDE, (w + 1) * STRIDE)
        marks = np.fromiter((m.start() for m in _TRIGGER.finditer(text)), np.int64)
        if len(marks):
            low, high = np.maximum(marks - WINDOW + MARGIN + STRIDE, 0) // STRIDE, (marks + MARGIN) // STRIDE
            near = np.unique(np.concatenate([low, marks // STRIDE, np.minimum(high, (len(text) - 1) // STRIDE)]))
            jobs += [(i, int(w)) for w in near]
    labels: dict[tuple[int, int], np.ndarray] = {}
    found: list[list[tuple[int, int, int]]] = [[] for _ in texts]
    by_text: dict[int, list[int]] = {}
    while jobs:
        _decode(texts, tagger, jobs, labels, most)
        for i, w in jobs:
            by_text.setdefault(i, []).append(w)
        changed, jobs = sorted({i for i, _ in jobs}), []
        for i in changed:
            found[i], beyond = _join(texts[i], i, sorted(by_text[i]), labels)
            jobs += [(i, w) for w in beyond]
    return found


def _decode(texts: list[str], tagger: Tagger, jobs: list[tuple[int, int]], labels: dict, most: int) -> None:
    """Adds to labels what the windows in jobs decide."""
    known: tuple[int, np.ndarray] = (-1, np.empty(0))
    for k in range(0, len(jobs), most):
        part = jobs[k : k + most]
        ids = np.full((len(part), WINDOW), PAD, np.int64)
        for r, (i, w) in enumerate(part):
            if known[0] != i:
                known = (i, classes(texts[i]))
            a = w * STRIDE - MARGIN
            piece = known[1][max(a, 0) : a + WINDOW]
            ids[r, max(-a, 0) : max(-a, 0) + len(piece)] = piece
        for (i, w), row in zip(part, tagger.decode(ids)):
            labels[i, w] = row[MARGIN : MARGIN + STRIDE]


def _join(text: str, i: int, ws: list[int], labels: dict) -> tuple[list[tuple[int, int, int]], list[int]]:
    """Spans of what neighbouring windows decided, and the windows still to decode as a span reaches them."""
    spans, beyond, last = [], set(), (len(text) - 1) // STRIDE
    for run in np.split(np.array(ws), np.flatnonzero(np.diff(ws) != 1) + 1):
        row = np.concatenate([labels[i, int(w)] for w in run])
        start = int(run[0]) * STRIDE
        row = row[: len(text) - start]
        for kind, a, b in _read(row, start, text):
            spans.append((kind, a, b))
            if a == start and run[0] > 0:
                beyond.add(int(run[0]) - 1)
            if b == start + len(row) and run[-1] < last:
                beyond.add(int(run[-1]) + 1)
    return spans, sorted(beyond)


def _read(row: np.ndarray, offset: int, text: str):
    """Spans of a label sequence: B starts one, I goes on with the same kind or starts one."""
    kind = (row - 1) // 2
    inside = row > 0
    begins = inside & ((row % 2 == 1) | np.concatenate([[True], (kind[1:] != kind[:-1]) | ~inside[:-1]]))
    for a in np.flatnonzero(begins):
        b = a + 1
        while b < len(row) and inside[b] and not begins[b]:
            b += 1
        piece = text[offset + a : offset + b]
        if _TRIGGER.search(piece):
            yield int(kind[a]), int(offset + a), int(offset + b)


def plausible(kind: int, piece: str) -> bool:
    """Whether a span of the model can be of its kind: the checks that numbers of that kind always pass."""
    digits = re.sub("[^0-9]", "", piece)
    if kind == 0:
        return "@" in piece and "." in piece.partition("@")[2]
    if kind == 1:
        parts = piece.split(".")
        return len(parts) == 4 and all(x.isascii() and x.isdigit() and len(x) <= 3 and int(x) <= 255 for x in parts)
    if kind == 2:
        return 13 <= len(digits) <= 19 and luhn(digits)
    return 9 <= len(digits) <= 15


def spans_of(texts: list[str], tagger: Tagger) -> list[tuple[list, list]]:
    """(base spans, all spans) of each text."""
    out = []
    for text, extra in zip(texts, model_spans(texts, tagger)):
        base = base_spans(text)
        added = [s for s in extra if plausible(s[0], text[s[1] : s[2]]) and not any(s[1] < b and a < s[2] for _, a, b in base)] if extra else []
        out.append((base, sorted(base + added)))
    return out


def _said(spans) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for k, a, b in spans)


def _scan(shared):
    def run(batches):
        tagger = Tagger()
        tagger.p = shared.value
        for batch in batches:
            texts = batch.column(1).to_pylist()
            found = spans_of(texts, tagger)
            counts = [pa.array([sum(s[0] == k for s in base) for base, _ in found], pa.int64()) for k in range(len(KINDS))]
            digests = pa.array([hashlib.sha256(_said(base).encode()).hexdigest() for base, _ in found], pa.string())
            said = pa.array([_said(all_) for _, all_ in found], pa.string())
            yield pa.RecordBatch.from_arrays([batch.column(0), *counts, digests, said], names=["doc_id", *[f"n_{k}" for k in KINDS], "base_sha256", "spans"])

    return run


def scan(docs: DataFrame, tagger: Tagger | None = None) -> DataFrame:
    """One row per row of docs: doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast((tagger or trained()).p)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return rows.mapInArrow(_scan(shared), "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string")
