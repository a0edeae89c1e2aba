"""Personal data: fixed patterns plus a character-level bidirectional LSTM with CRF transitions.

The network is written and trained in numpy from labelled spans: those that the fixed patterns find in a bounded sample
of documents (SAMPLE_DOCS, of SAMPLE_CHARS at most), each also in altered forms that the patterns do not know (a phone number without "+",
other separators, a card number in odd groups), in surroundings drawn from all the sample. Inference scores overlapping
windows of each text, joins the scores of windows that overlap, and runs one Viterbi path over each joined stretch. Spans of the patterns always stay; a span of the network is added if it does not
touch one of them, is plausible for its kind (number of digits, check digit) and its labels are sure enough.

A span of any of the four kinds must hold a digit or "@": windows further than one window from both are not scored, so a span
is found as far as it lies within a window's length of one of its digits or its "@".

Defined cases: null text counts as empty and gives the digest of ""; repeated rows stay rows; with no labelled span in
the sample the network is not trained and the patterns alone count.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathweave.llm import common as C

KINDS = ("email", "ip", "card", "phone")
WINDOW, STRIDE, HIDDEN, EMBED = 96, 48, 20, 12
SAMPLE_DOCS, SAMPLE_CHARS, SAMPLE_WINDOWS, EPOCHS, SURE = 400, 20_000, 3200, 12, 0.8
TAGS = 1 + 2 * len(KINDS)  # outside, then begin and inside of each kind

# ------------------------------------------------------------------ fixed patterns
_LOCAL = re.compile(r"[A-Za-z0-9._%+-]")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_MARK = re.compile(r"[0-9@]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches of the e-mail pattern; each character before an @ is looked at once."""
    out, cur, at = [], 0, text.find("@")
    while at >= 0:
        s = at
        while s > cur and _LOCAL.match(text, s - 1):
            s -= 1
        if s < at and (m := _DOMAIN.match(text, at + 1)):
            out.append((s, m.end()))
            cur = m.end()
        else:
            cur = at + 1
        at = text.find("@", max(cur, at + 1))
    return out


def base_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    if not _MARK.search(text):
        return out
    out["email"] = emails(text)
    out["ip"] = [m.span() for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        d = m[0].replace(" ", "").replace("-", "")
        if 16 <= len(d) <= 19 and luhn(d):
            out["card"].append(m.span())
    out["phone"] = [m.span() for m in _PHONE.finditer(text) if 8 <= sum(c.isdigit() for c in m[0]) <= 15]
    return out


# ------------------------------------------------------------------ the network
def encode(text: str) -> np.ndarray:
    """Character numbers: ASCII for itself, letters of Latin scripts as one, other letters as one, the rest as one."""
    x = np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)
    return np.where(x < 128, x, np.where(x < 0x250, 128, np.where(x < 0x2000, 129, 130))).astype(np.int64)


CHARS = 132
PAD = 131


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def _lstm(x, wx, wh, b):
    """x: time, batch, input. Returns outputs and what the backward pass needs."""
    n, m, h = x.shape[0], x.shape[1], wh.shape[0]
    pre = x @ wx + b
    hs, cs, gates = np.zeros((n + 1, m, h), np.float32), np.zeros((n + 1, m, h), np.float32), np.zeros((n, m, 4 * h), np.float32)
    for t in range(n):
        z = pre[t] + hs[t] @ wh
        g = gates[t]
        g[:, : 3 * h] = _sigmoid(z[:, : 3 * h])
        g[:, 3 * h :] = np.tanh(z[:, 3 * h :])
        cs[t + 1] = g[:, h : 2 * h] * cs[t] + g[:, :h] * g[:, 3 * h :]
        hs[t + 1] = g[:, 2 * h : 3 * h] * np.tanh(cs[t + 1])
    return hs[1:], (x, hs, cs, gates)


def _lstm_back(dout, kept, wx, wh):
    x, hs, cs, gates = kept
    n, m, h = dout.shape
    dz = np.zeros((n, m, 4 * h), np.float32)
    dh, dc = np.zeros((m, h), np.float32), np.zeros((m, h), np.float32)
    for t in range(n - 1, -1, -1):
        i, f, o, g = np.split(gates[t], 4, axis=1)
        dh = dh + dout[t]
        tc = np.tanh(cs[t + 1])
        dc = dc + dh * o * (1 - tc * tc)
        dz[t] = np.concatenate([dc * g * i * (1 - i), dc * cs[t] * f * (1 - f), dh * tc * o * (1 - o), dc * i * (1 - g * g)], axis=1)
        dc = dc * f
        dh = dz[t] @ wh.T
    flat = dz.reshape(-1, 4 * h)
    return dz @ wx.T, x.reshape(-1, x.shape[2]).T @ flat, hs[:-1].reshape(-1, h).T @ flat, flat.sum(0)


def _logsum(x, axis):
    m = x.max(axis=axis, keepdims=True)
    return (m + np.log(np.exp(x - m).sum(axis=axis, keepdims=True))).squeeze(axis)


def allowed() -> np.ndarray:
    """Transitions that a label sequence can have: inside only after begin or inside of the same kind."""
    ok = np.ones((TAGS, TAGS), bool)
    for k in range(len(KINDS)):
        inside = 2 + 2 * k
        ok[:, inside] = False
        ok[[inside - 1, inside], inside] = True
    return ok


BARRED = np.where(allowed(), 0, -1e4).astype(np.float32)


class Tagger:
    def __init__(self, seed: int = 3):
        r = np.random.default_rng(seed)
        h, e = HIDDEN, EMBED
        mat = lambda a, b: (r.standard_normal((a, b)) / np.sqrt(a)).astype(np.float32)
        self.p = {"emb": mat(CHARS, e), "trans": np.zeros((TAGS, TAGS), np.float32), "out": mat(2 * h, TAGS), "bias": np.zeros(TAGS, np.float32)}
        for d in "lr":
            self.p |= {f"{d}x": mat(e, 4 * h), f"{d}h": mat(h, 4 * h), f"{d}b": np.zeros(4 * h, np.float32)}
            self.p[f"{d}b"][h : 2 * h] = 1

    def scores(self, x: np.ndarray):
        """x: time, batch of character numbers -> emissions and what the backward pass needs."""
        p = self.p
        v = p["emb"][x]
        left, kl = _lstm(v, p["lx"], p["lh"], p["lb"])
        right, kr = _lstm(v[::-1], p["rx"], p["rh"], p["rb"])
        both = np.concatenate([left, right[::-1]], axis=2)
        return both @ p["out"] + p["bias"], (x, both, kl, kr)

    def marginals(self, e: np.ndarray):
        """Log forward and backward sums of the chain, and the log of their total."""
        t = self.p["trans"] + BARRED
        n = len(e)
        start = e[0].copy()
        start[:, 2::2] -= 1e4
        a, b = np.zeros_like(e), np.zeros_like(e)
        a[0] = start
        for i in range(1, n):
            a[i] = _logsum(a[i - 1][:, :, None] + t, 1) + e[i]
        for i in range(n - 2, -1, -1):
            b[i] = _logsum(t + (e[i + 1] + b[i + 1])[:, None, :], 2)
        return a, b, _logsum(a[-1], 1), t

    def loss(self, x: np.ndarray, y: np.ndarray) -> float:
        """Negative log likelihood of the labels, summed over the batch."""
        e, _ = self.scores(x)
        _, _, z, t = self.marginals(e)
        n, m = x.shape
        own = e[np.arange(n)[:, None], np.arange(m)[None, :], y].sum(0) + t[y[:-1], y[1:]].sum(0)
        return float((z - own).sum())

    def gradients(self, x: np.ndarray, y: np.ndarray) -> dict:
        e, (_, both, kl, kr) = self.scores(x)
        a, b, z, t = self.marginals(e)
        n, m = x.shape
        de = np.exp(np.clip(a + b - z[None, :, None], -50, 0))
        pair = np.exp(np.clip(a[:-1][:, :, :, None] + t + (e[1:] + b[1:])[:, :, None, :] - z[None, :, None, None], -50, 0)).sum((0, 1))
        np.add.at(de, (np.arange(n)[:, None], np.arange(m)[None, :], y), -1)
        seen = np.zeros_like(pair)
        np.add.at(seen, (y[:-1], y[1:]), 1)
        g = {"trans": (pair - seen) * (BARRED == 0)}
        de = de.astype(np.float32)
        flat = de.reshape(-1, TAGS)
        g["out"], g["bias"] = both.reshape(-1, both.shape[2]).T @ flat, flat.sum(0)
        d = de @ self.p["out"].T
        h = HIDDEN
        vl, g["lx"], g["lh"], g["lb"] = _lstm_back(d[:, :, :h], kl, self.p["lx"], self.p["lh"])
        vr, g["rx"], g["rh"], g["rb"] = _lstm_back(d[::-1, :, h:], kr, self.p["rx"], self.p["rh"])
        g["emb"] = np.zeros_like(self.p["emb"])
        np.add.at(g["emb"], x, vl + vr[::-1])
        return g

    def step(self, x, y, state, rate):
        state["n"] = state.get("n", 0) + 1
        for k, v in self.gradients(x, y).items():  # Adam
            v = np.clip(v / x.shape[1], -1, 1)
            mo, sq = state.get(k, (0.0, 0.0))
            mo, sq = 0.9 * mo + 0.1 * v, 0.99 * sq + 0.01 * v * v
            state[k] = (mo, sq)
            self.p[k] = (self.p[k] - rate * (mo / (1 - 0.9 ** state["n"])) / (np.sqrt(sq / (1 - 0.99 ** state["n"])) + 1e-6)).astype(np.float32)

    def fit(self, texts: list[tuple[str, np.ndarray]], epochs: int = EPOCHS, batch: int = 64, seed: int = 5):
        r, state = np.random.default_rng(seed), {}
        x = np.full((len(texts), WINDOW), PAD, np.int64)
        y = np.zeros((len(texts), WINDOW), np.int64)
        for i, (s, tags) in enumerate(texts):
            x[i, : len(s)], y[i, : len(s)] = encode(s), tags
        for ep in range(epochs):
            order = r.permutation(len(texts))
            for k in range(0, len(order), batch):
                o = order[k : k + batch]
                self.step(x[o].T, y[o].T, state, 0.02 if ep < epochs - 3 else 0.005)
        return self

    def decode(self, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Viterbi labels of emissions (time, batch, labels) and the labels' marginal probabilities."""
        a, b, z, t = self.marginals(e)
        n, m = e.shape[:2]
        best = e[0].copy()
        best[:, 2::2] -= 1e4
        back = np.zeros((n, m, TAGS), np.int8)
        for i in range(1, n):
            s = best[:, :, None] + t
            back[i] = s.argmax(1)
            best = s.max(1) + e[i]
        tags = np.zeros((n, m), np.int64)
        tags[-1] = best.argmax(1)
        for i in range(n - 1, 0, -1):
            tags[i - 1] = back[i, np.arange(m), tags[i]]
        sure = np.exp(np.clip(a + b - z[None, :, None], -50, 0))
        return tags, np.take_along_axis(sure, tags[:, :, None], 2)[:, :, 0]


# ------------------------------------------------------------------ labelled spans
def _luhn_digits(n: int, r: np.random.Generator) -> str:
    d = "".join(str(x) for x in r.integers(0, 10, n - 1))
    return next(d + str(c) for c in range(10) if luhn(d + str(c)))


def _grouped(d: str, by: str, size: int = 4) -> str:
    return by.join(d[i : i + size] for i in range(0, len(d), size))


def altered(kind: str, s: str, r: np.random.Generator) -> list[str]:
    """Forms of a span, with new digits, that the patterns may not know."""
    if kind == "phone":
        d = str(r.integers(2, 10)) + "".join(str(x) for x in r.integers(0, 10, 9))
        return [f"({d[:3]}) {d[3:6]}-{d[6:]}", f"{d[:3]}-{d[3:6]}-{d[6:]}", f"{d[:3]}.{d[3:6]}.{d[6:]}", f"{d[:3]} {d[3:6]} {d[6:]}", f"00{r.integers(1, 99)}{d}"]
    if kind == "card":
        d = _luhn_digits(int(r.choice([14, 15, 16, 16])), r)
        return [d, _grouped(d, " "), _grouped(d, "-"), _grouped(d, ".")]
    if kind == "email":
        # Another name of the same make at the same top domain.
        name = "".join(chr(int(r.integers(97, 123))) if c.isalpha() else c for c in s.lower())
        host, _, top = name.rpartition(".")
        name = f"{host}.{s.lower().rpartition('.')[2]}" if top else name
        return [name.upper(), name.replace("@", " @ "), name.replace("@", " @"), name.replace("@", "@ ")]
    return [".".join(str(x) for x in r.integers(0, 256, 4))]


def _other(r: np.random.Generator) -> str:
    """Digits or signs that are nobody's."""
    n = lambda a, b: int(r.integers(a, b))
    return [str(n(0, 10)), str(n(10, 10_000)), f"{n(1990, 2030)}", f"{n(1, 10)}.{n(0, 100)}", f"{n(1, 100)},{n(100, 1000)}", f"{n(1, 100)}%", f"v{n(1, 10)}.{n(0, 20)}.{n(0, 20)}", "@",
            f"{n(1900, 2030)}-{n(1, 13):02d}-{n(1, 29):02d}", f"{n(1, 29):02d}.{n(1, 13):02d}.{n(1990, 2030)}", f"${n(1, 1000)}", f"{n(0, 24)}:{n(0, 60):02d}", f"#{n(1, 10**7)}", f"@name{n(1, 99)}"][n(0, 14)]


def training_windows(texts: list[str], most: int = SAMPLE_WINDOWS, seed: int = 11, forms_of=altered) -> list[tuple[str, np.ndarray]]:
    """Windows around the labelled spans, as they are and in altered forms, each at a place of its own in surroundings drawn from all the
    texts, and as many windows with other digits or signs. Kinds take turns, so a rare one has its share."""
    r = np.random.default_rng(seed)
    places = [(t, s, e) for t in texts for v in base_spans(t).values() for s, e in v]
    by_kind: list[list[tuple[str, str]]] = [[] for _ in KINDS]
    for t in texts:
        found = base_spans(t)
        for k, kind in enumerate(KINDS):
            by_kind[k] += [(t[s:e], kind) for s, e in found[kind] if e - s <= WINDOW - 8]
    plain = lambda x: re.sub(r"[0-9@+]", "x", x)
    out: list[tuple[str, np.ndarray]] = []
    turn = 0
    while any(by_kind) and len(out) < most:
        k = turn % len(KINDS)
        turn += 1
        if not by_kind[k]:
            continue
        span, kind = by_kind[k][(turn // len(KINDS)) % len(by_kind[k])]
        more = forms_of(kind, span, r)
        form = span if r.random() < 0.3 else more[int(r.integers(len(more)))]
        if len(form) > WINDOW - 4:
            continue
        for what, label in ((form, k), (_other(r), None)):
            t, s, e = places[int(r.integers(len(places)))]
            room = WINDOW - len(what)
            left = int(r.integers(0, room + 1))
            # Half of the time the surroundings are those of no other span's place.
            if r.random() < 0.5:
                s = e = int(r.integers(0, len(t) + 1))
            a, z = plain(t[max(0, s - left) : s]), plain(t[e : e + room - left])
            a = a + " " if a and a[-1].isalnum() else a
            z = " " + z if z and z[0].isalnum() else z
            w = (a + what + z)[:WINDOW]
            tags = np.zeros(len(w), np.int64)
            if label is not None:
                tags[len(a) : len(a) + len(what)] = 2 + 2 * label
                if len(a) < len(w):
                    tags[len(a)] = 1 + 2 * label
            out.append((w, tags))
    order = r.permutation(len(out))
    return [out[i] for i in order]


def plausible(kind: str, s: str) -> bool:
    d = re.sub(r"[^0-9]", "", s)
    if kind == "email":
        return bool(re.fullmatch(r"\S+ ?@ ?[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", s))
    if kind == "ip":
        p = re.split(r"[^0-9]+", s)
        return len(p) == 4 and all(x and len(x) <= 3 and int(x) <= 255 for x in p)
    if kind == "card":
        return 13 <= len(d) <= 19 and luhn(d) and not re.search(r"[^0-9 .-]", s)
    return 10 <= len(d) <= 15 and not re.search(r"[^0-9 ().+-]", s) and bool(re.search(r"[0-9][ ().-]+[0-9]|^00", s))


def windows_of(text: str) -> np.ndarray:
    """Numbers of the windows around digits and "@", with the next one on each side; window k starts at character k * STRIDE."""
    marks = np.array([m.start() for m in _MARK.finditer(text)], np.int64)
    if not len(marks):
        return marks
    last = max(0, -(-(len(text) - WINDOW) // STRIDE))
    at = np.unique(marks // STRIDE)
    return np.unique(np.clip((at[:, None] + np.arange(-2, 2)).reshape(-1), 0, last))


#: How much a window's scores count for each of its characters: most in its middle.
_WEIGHT = np.minimum(np.arange(WINDOW) + 1, WINDOW - np.arange(WINDOW)).astype(np.float32)[:, None]


def read_spans(texts: list[str], tagger: Tagger, most: int = 512) -> list[list[tuple[str, int, int]]]:
    """The network's spans of each text. Windows of all texts are scored together; where they overlap, a character's scores are the
    weighted mean of its windows', and one Viterbi path runs over each joined stretch, so labels are a legal sequence across
    windows."""
    codes = [encode(t) for t in texts]
    todo, pieces = [], []  # (stretch, text, window); [text, first character, scores, weights]
    for r, t in enumerate(texts):
        before = None
        for k in windows_of(t).tolist():
            if before is None or k != before + 1:
                pieces.append([r, k * STRIDE, 0])
            pieces[-1][2] = min(len(t), k * STRIDE + WINDOW)
            todo.append((len(pieces) - 1, r, k))
            before = k
    sums = [np.zeros((end - a, TAGS), np.float32) for _, a, end in pieces]
    weights = [np.zeros((end - a, 1), np.float32) for _, a, end in pieces]
    for c in range(0, len(todo), most):
        some = todo[c : c + most]
        x = np.full((len(some), WINDOW), PAD, np.int64)
        for i, (_, r, k) in enumerate(some):
            piece = codes[r][k * STRIDE : k * STRIDE + WINDOW]
            x[i, : len(piece)] = piece
        e = tagger.scores(x.T)[0]
        for i, (p, r, k) in enumerate(some):
            a = k * STRIDE - pieces[p][1]
            m = min(WINDOW, len(sums[p]) - a)
            sums[p][a : a + m] += e[:m, i] * _WEIGHT[:m]
            weights[p][a : a + m] += _WEIGHT[:m]
    out: list[list] = [[] for _ in texts]
    order, at = sorted(range(len(pieces)), key=lambda p: len(sums[p])), 0
    while at < len(order):
        # Stretches of about one length at a time, so many that the lattice stays small.
        n = max(1, min(most, (1 << 16) // max(1, len(sums[order[at]]))))
        some = order[at : at + n]
        while len(some) > 1 and len(sums[some[-1]]) > 2 * len(sums[some[0]]) + WINDOW:
            some = some[: len(some) // 2]
        at += len(some)
        long = len(sums[some[-1]])
        lattice = np.full((long, len(some), TAGS), -1e4, np.float32)
        lattice[:, :, 0] = 0  # beyond a stretch's end there is nothing
        for i, p in enumerate(some):
            lattice[: len(sums[p]), i] = sums[p] / weights[p]
        tags, sure = tagger.decode(lattice)
        for i, p in enumerate(some):
            r, a, _ = pieces[p]
            out[r] += spans_in(texts[r], a, tags[: len(sums[p]), i], sure[: len(sums[p]), i])
    return [sorted(set(x), key=lambda y: y[1:]) for x in out]


def spans_in(text: str, at: int, tags: np.ndarray, sure: np.ndarray) -> list[tuple[str, int, int]]:
    """The sure and plausible spans in the labels of a stretch that starts at a character."""
    out, n = [], len(text)
    for s in np.flatnonzero(tags % 2 == 1).tolist():
        kind, e = (int(tags[s]) - 1) // 2, s + 1
        while e < len(tags) and tags[e] == 2 + 2 * kind:
            e += 1
        a, z = s + at, e + at
        while z > a and text[z - 1] in " .,;":
            z -= 1
        while a < z and text[a] in " .,;":
            a += 1
        if z > a and sure[a - at : z - at].mean() >= SURE and _MARK.search(text, a, z) and plausible(KINDS[kind], text[a:z]):
            # Part of a longer run of digits or letters is no span.
            if not (a and text[a - 1].isalnum() and text[a].isalnum()) and not (z < n and text[z].isalnum() and text[z - 1].isalnum()):
                out.append((KINDS[kind], a, z))
    return out


def shown(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


def marked(col: pa.Array, most_chars: int = 1 << 20) -> Iterator[tuple[list[int], list[str]]]:
    """Rows whose text has a digit or "@", with their texts, about most_chars characters at a time."""
    rows, texts, held = [], [], 0
    for r, text in enumerate(col):
        text = text.as_py()
        if text and _MARK.search(text):
            rows.append(r), texts.append(text)
            held += len(text)
            if held >= most_chars:
                yield rows, texts
                rows, texts, held = [], [], 0
    if rows:
        yield rows, texts


def finder(model):
    """mapInArrow function: doc_id, text -> counts, digest and spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger = None
        if model.value is not None:
            tagger = Tagger.__new__(Tagger)
            tagger.p = model.value
        empty = hashlib.sha256(b"").hexdigest()
        for batch in batches:
            n = batch.num_rows
            counts, digest, spans, added = [(0, 0, 0, 0)] * n, [empty] * n, [""] * n, [0] * n
            for rows, texts in marked(batch.column(1)):
                own = read_spans(texts, tagger) if tagger is not None else [[]] * len(texts)
                for r, text, more in zip(rows, texts, own):
                    found = base_spans(text)
                    base = [(k, s, e) for k in KINDS for s, e in found[k]]
                    more = [x for x in more if all(x[2] <= s or e <= x[1] for _, s, e in base)]
                    every = sorted({*base, *more}, key=lambda x: (KINDS.index(x[0]), x[1], x[2]))
                    counts[r], digest[r], spans[r], added[r] = tuple(len(found[k]) for k in KINDS), hashlib.sha256(shown(base).encode()).hexdigest(), shown(every), len(more)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array([c[i] for c in counts], pa.int64()) for i in range(4)), pa.array(digest, pa.string()), pa.array(spans, pa.string()), pa.array(added, pa.int64())],
                ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_added"],
            )

    return run


def train(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> dict | None:
    """Parameters of the network, from the fixed patterns' spans in at most sample_docs documents."""
    holds = F.col("text").rlike(r"@[A-Za-z0-9-]+\.[A-Za-z0-9]|\+[0-9][ ().0-9-]{6}|[0-9][0-9 -]{14}|[0-9]\.[0-9]+\.[0-9]+\.[0-9]")
    some = docs.filter(holds & (F.length("text") <= SAMPLE_CHARS)).select("text", F.xxhash64("text").alias("h"))
    # Numbers first, then the few texts below the last of them: no task sends texts that are not taken.
    least = [r["h"] for r in some.select("h").distinct().orderBy("h").limit(sample_docs).collect()]
    if not least:
        return None
    some = some.filter(F.col("h") <= max(least)).dropDuplicates(["h"]).orderBy("h").collect()
    windows = training_windows([r["text"] for r in some])
    return Tagger().fit(windows).p if windows else None


def personal_data(docs: DataFrame, sample_docs: int = SAMPLE_DOCS, model: dict | None = None) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added."""
    docs = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    sent = docs.sparkSession.sparkContext.broadcast(model or train(docs, sample_docs))
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long"
    return docs.mapInArrow(finder(sent), schema)


def masked(docs: DataFrame, model: dict | None = None) -> DataFrame:
    """docs with every found span of text replaced by its kind in angle brackets; other columns and rows stay."""
    sent = docs.sparkSession.sparkContext.broadcast(model or train(docs.select(F.col("text").cast("string").alias("text"))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger = None
        if sent.value is not None:
            tagger = Tagger.__new__(Tagger)
            tagger.p = sent.value
        for batch in batches:
            k = batch.schema.get_field_index("text")
            out = batch.column(k).to_pylist()
            for rows, texts in marked(batch.column(k)):
                own = read_spans(texts, tagger) if tagger is not None else [[]] * len(texts)
                for r, text, more in zip(rows, texts, own):
                    spans = [(s, e, kind) for kind, v in base_spans(text).items() for s, e in v]
                    spans += [(s, e, kind) for kind, s, e in more if all(e <= a or z <= s for a, z, _ in spans)]
                    # Overlapping spans go as one; the longest names the kind.
                    joined: list[list] = []
                    for s, e, kind in sorted(spans):
                        if joined and s < joined[-1][1]:
                            joined[-1][1] = max(joined[-1][1], e)
                            joined[-1][2] = max(joined[-1][2], (e - s, kind), key=lambda x: x[0])
                        else:
                            joined.append([s, e, (e - s, kind)])
                    parts, at = [], 0
                    for s, e, (_, kind) in joined:
                        parts += [text[at:s], f"<{kind}>"]
                        at = e
                    out[r] = "".join([*parts, text[at:]])
            yield batch.set_column(k, batch.schema.field(k), pa.array(out, batch.schema.field(k).type))

    return docs.mapInArrow(run, docs.schema)
