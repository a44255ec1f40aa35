"""A linear-chain conditional random field over word shapes: likelihood training and Viterbi decoding in numpy batches.

A sequence is one line: a list of tokens, each a number that packs its shape and its cue. Features are combinations of shapes and cues
of neighbouring tokens, named by 64-bit numbers that a sorted table turns into rows of weights; features that training has not seen weigh nothing."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np

TOKEN = re.compile(r"\w+|[^\w\s]")
# Words that hint at personal data, or at harmless numbers, near them.
CUES = ["at", "dot", "mail", "email", "tel", "phone", "call", "fax", "mobile", "card", "visa", "ip", "host", "address", "version", "order", "page", "id", "invoice", "room", "com", "org", "net", "password", "passwd", "pwd", "token", "secret", "key", "api", "apikey", "bearer", "auth", "commit", "sha", "sha1", "sha256", "md5", "digest", "checksum", "revision"]
_CUE = {w: i + 1 for i, w in enumerate(CUES)}
EDGE = 1  # the shape beyond either end of a line; 0 is a shape that training has not seen
NEVER = -1e4
TEMPLATES = 14


def shape(token: str) -> str:
    """Letters become a or A, runs of them short; digits become 9, one each up to four; long mixtures of letters and digits have names of their own."""
    if token.isdigit():
        return "9" * min(len(token), 4) + ("+" if len(token) > 4 else "") + ("+" if len(token) > 12 else "")
    if len(token) >= 12 and token.isascii() and token.replace("_", "").isalnum() and any(c.isdigit() for c in token):
        return "hex" if re.fullmatch("[0-9a-f]+", token) else "CODE" if token.isupper() else "Mixed"
    if len(token) >= 16 and token.isascii() and token.isalpha() and token.isupper():
        return "CODE"
    s = re.sub(r"[^\W\d_]", lambda m: "A" if m[0].isupper() else "a", token)
    s = re.sub(r"\d", "9", s)
    return re.sub(r"(.)\1+", r"\1+", s) if len(s) > 1 else s


def tokenize(text: str) -> list[tuple[int, int]]:
    return [m.span() for m in TOKEN.finditer(text)]


class ShapeCRF:
    """States are O and B-, I- of each kind; I- follows only B- or I- of its kind."""

    def __init__(self, kinds: list[str]):
        self.kinds = kinds
        self.states = ["O", *(f"{p}-{k}" for k in kinds for p in "BI")]
        self.shapes: dict[str, int] = {}
        self.memo: dict[str, int] = {}
        s = len(self.states)
        self.allowed = np.array([[0.0 if b[0] != "I" or a[1:] == b[1:] else NEVER for b in self.states] for a in self.states])
        self.start_allowed = np.array([NEVER if b[0] == "I" else 0.0 for b in self.states])
        self.keys, self.emit, self.move = np.zeros(0, np.int64), np.zeros((1, s)), np.zeros((s, s))

    def codes(self, words: list[str], grow: bool = False) -> np.ndarray:
        """Shape and cue of each token as one number."""
        get, out = self.memo, []
        for w in words:
            x = get.get(w)
            if x is None:
                name = shape(w)
                number = self.shapes.setdefault(name, len(self.shapes) + 2) if grow else self.shapes.get(name, 0)
                x = number << 6 | _CUE.get(w.lower(), 0)
                if len(get) < 200_000:
                    get[w] = x
            out.append(x)
        return np.array(out, np.int64)

    @staticmethod
    def features(code: np.ndarray, joined: np.ndarray, first: np.ndarray, last: np.ndarray) -> Iterator[np.ndarray]:
        """For each template the feature number of each token of consecutive lines. joined: whether no blank stands before the token; first,
        last: tokens before and after it in its line."""
        n, at = len(code), np.arange(len(code))

        def near(x: np.ndarray, step: int, edge: int) -> np.ndarray:
            inside = (first >= -step) if step < 0 else (last >= step)
            return np.where(inside, x[np.clip(at + step, 0, max(n - 1, 0))], edge)

        s, cue = code >> 6, code & 63
        s1, s2, s3, s4, j1 = near(s, -1, EDGE), near(s, 1, EDGE), near(s, -2, EDGE), near(s, 2, EDGE), near(joined, 1, 2)
        made = [(s, 0, 0), (s1, s, 0), (s, s2, 0), (s3, s1, 0), (s2, s4, 0), (s1, s, s2), (s3, s1, s), (s, s2, s4), (s, joined * 3 + j1, 0)]
        made += [(near(cue, d, 63), s if d else 0, 0) for d in (0, -1, 1, -2, -3)]
        for t, (a, b, c) in enumerate(made):
            yield (a << 20 | b) << 20 | c | np.int64(t) << 59

    def scores(self, code: np.ndarray, joined: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        out = np.zeros((len(code), len(self.states)))
        for key in self.features(code, joined, first, last):
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            hit = np.flatnonzero(self.keys[at] == key)
            out[hit] += self.emit[at[hit]]
        return out

    def fit(self, rows: list[tuple[str, list[tuple[str, int, int]]]], steps: int = 70, rate: float = 0.25, penalty: float = 1e-3) -> ShapeCRF:
        """rows: (line, [(kind, start, end)]). Maximises the penalised conditional likelihood with full-batch Adam."""
        lines = [Line(text, self, True) for text, _ in rows]
        gold = []
        for line, (_, spans) in zip(lines, rows, strict=True):
            y = np.zeros(len(line.tokens), np.int64)
            for kind, a, b in spans:
                inside = [i for i, (s, e) in enumerate(line.tokens) if s >= a and e <= b]
                y[inside] = self.states.index(f"I-{kind}")
                y[inside[:1]] = self.states.index(f"B-{kind}")
            gold.append(y)
        order = sorted((i for i in range(len(rows)) if len(gold[i])), key=lambda i: -len(gold[i]))
        if not order:
            return self
        y, batch = np.concatenate([gold[i] for i in order]), together([lines[i] for i in order])
        found = np.stack(list(self.features(*batch)))
        self.keys, x = np.unique(found, return_inverse=True)
        x = x.reshape(found.shape)
        by = np.argsort(x.ravel(), kind="stable")
        lead, token = np.searchsorted(x.ravel()[by], np.arange(len(self.keys))), by % len(y)
        size, s = np.array([len(gold[i]) for i in order]), len(self.states)
        self.emit, self.move = np.zeros((len(self.keys), s)), np.zeros((s, s))
        gold_moves = np.zeros((s, s))
        for i in order:
            np.add.at(gold_moves, (gold[i][:-1], gold[i][1:]), 1)
        params, onehot = [self.emit, self.move], np.eye(s)[y]
        m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        for step in range(1, steps + 1):
            own, moves, _ = self.expected(sum(self.emit[i] for i in x), size)
            g_emit = np.add.reduceat((onehot - own)[token], lead, axis=0)
            for p, g, a, b in zip(params, (g_emit / len(order) - penalty * self.emit, (gold_moves - moves) / len(order) - penalty * self.move), m, v, strict=True):
                a += 0.1 * (g - a)
                b += 0.01 * (g * g - b)
                p += rate * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.99**step)) + 1e-8)
        return self

    def stored(self) -> dict:
        """All of the model as a row of plain columns."""
        return {"kinds": list(self.kinds), "shapes": list(self.shapes), "keys": self.keys.tobytes(), "emit": self.emit.tobytes(), "move": self.move.tobytes()}

    @classmethod
    def restored(cls, row: dict) -> ShapeCRF:
        model = cls(list(row["kinds"]))
        model.shapes = {name: i + 2 for i, name in enumerate(row["shapes"])}
        s = len(model.states)
        model.keys, model.emit, model.move = np.frombuffer(row["keys"], np.int64), np.frombuffer(row["emit"]).reshape(-1, s), np.frombuffer(row["move"]).reshape(s, s)
        return model

    def expected(self, score: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """Forward and backward pass over lines of falling sizes: probabilities of the states of each token, expected transitions, log of the sums."""
        start = np.concatenate([[0], np.cumsum(size)[:-1]])
        live = [int((size > t).sum()) for t in range(int(size[0]))]
        top = score.max(axis=1, keepdims=True)
        e, trans = np.exp(score - top), np.exp(self.move + self.allowed)
        fwd, norm = np.zeros_like(e), np.ones(len(e))
        for t, n in enumerate(live):
            at = start[:n] + t
            p = e[at] * (np.exp(self.start_allowed) if t == 0 else fwd[at - 1] @ trans)
            norm[at] = p.sum(axis=1)
            fwd[at] = p / norm[at][:, None]
        back, moves = np.ones_like(e), np.zeros_like(trans)
        for t in range(len(live) - 1, 0, -1):
            at = start[: live[t]] + t
            ahead = e[at] * back[at] / norm[at][:, None]
            back[at - 1] = ahead @ trans.T
            moves += trans * (fwd[at - 1].T @ ahead)
        return fwd * back, moves, float(np.log(norm).sum() + top.sum())

    def decode(self, lines: list[Line], cells: int = 1 << 18) -> list[np.ndarray]:
        """The best state sequence of each line (Viterbi); lines of like length advance together."""
        out: list[np.ndarray] = [np.zeros(0, np.int64)] * len(lines)
        order, trans, i = sorted((i for i in range(len(lines)) if lines[i].tokens), key=lambda i: -len(lines[i].tokens)), self.move + self.allowed, 0
        while i < len(order):
            group = order[i : i + max(1, cells // len(lines[order[i]].tokens))]
            i += len(group)
            size = np.array([len(lines[k].tokens) for k in group])
            score, start = self.scores(*together([lines[k] for k in group])), np.concatenate([[0], np.cumsum(size)[:-1]])
            back = np.zeros(score.shape, np.int8)
            best = score[start] + self.start_allowed
            final = np.zeros(len(group), np.int64)
            n = len(group)
            for t in range(1, int(size[0]) + 1):
                more = int((size[:n] > t).sum())
                final[more:n] = best[more:n].argmax(axis=1)
                n = more
                at = start[:n] + t
                z = best[:n, :, None] + trans
                back[at] = z.argmax(axis=1)
                best = z.max(axis=1) + score[at]
            path, state = np.zeros(len(score), np.int64), np.zeros(len(group), np.int64)
            for t in range(int(size[0]) - 1, -1, -1):
                n = int((size > t).sum())
                at = start[:n] + t
                ends = size[:n] == t + 1
                state[:n][ends] = final[:n][ends]
                path[at] = state[:n]
                state[:n] = back[at, state[:n]]
            for r, k in enumerate(group):
                out[k] = path[start[r] : start[r] + size[r]]
        return out

    def spans(self, tokens: list[tuple[int, int]], states: np.ndarray) -> list[tuple[str, int, int]]:
        """Token spans of the kinds in a state sequence, as (kind, start, end) of the text."""
        found = []
        for k in np.flatnonzero(states % 2 == 1).tolist():  # B-
            e = k + 1
            while e < len(states) and states[e] == states[k] + 1:
                e += 1
            found.append((self.states[states[k]][2:], tokens[k][0], tokens[e - 1][1]))
        return found


class Line:
    """The tokens of a line and their codes."""

    def __init__(self, text: str, model: ShapeCRF, grow: bool = False):
        self.tokens = tokenize(text)
        self.code = model.codes([text[a:b] for a, b in self.tokens], grow)


def together(lines: list[Line]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Arguments of `features` for consecutive lines."""
    size = np.array([len(x.tokens) for x in lines])
    spans = np.array([t for x in lines for t in x.tokens], np.int64).reshape(-1, 2)
    at = np.arange(len(spans)) - np.repeat(np.cumsum(size) - size, size)
    joined = np.zeros(len(spans), np.int64)
    joined[1:] = spans[1:, 0] == spans[:-1, 1]
    joined[at == 0] = 0
    return np.concatenate([x.code for x in lines]), joined, at, np.repeat(size, size) - 1 - at
