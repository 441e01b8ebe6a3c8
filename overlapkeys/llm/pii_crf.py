"""Operator 9: personal data by fixed patterns and a linear-chain conditional random field.

The patterns give the base spans. The field labels word-shape tokens of whole texts, is trained from a small
labelled table that a rule builds here, and is decoded by Viterbi over many token runs at once; it adds
spans that the patterns miss (numbers without a plus, spelled-out addresses) and never takes one away.

Inside a stretch of plain words where "other" leads by more than transitions can make up for, every best path is
"other". Which contexts are so is worked out once from the weights; the runs between such stretches are decoded
with transitions from and to "other", so the labels are those of decoding whole texts.
"""

from __future__ import annotations

import hashlib
import random
import re
from bisect import bisect_left
from collections.abc import Iterator
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, lean

# The base patterns.
KINDS = ("email", "ip", "card", "phone")
EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]++)(\.[0-9]++)(\.[0-9]++)")  # no start or retry inside a run of digits: same matches, linear time
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_LOCAL = re.compile(r"[A-Za-z0-9._%+-]+\Z")
_SPLIT_IP = re.compile(r"\.")

LABELS = ("o", *KINDS)


def _luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (1 + k % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def _octet(digits: str) -> bool:
    own = digits.lstrip("0")
    return len(own) <= 3 and int(own or "0") <= 255


def _emails(text: str) -> Iterator[tuple[int, int]]:
    """The matches of EMAIL, tried from each @ on: long runs without one cost nothing."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and _LOCAL.match(text[start - 1]):
            start -= 1
        m = EMAIL.match(text, start) if start < at else None
        if m:
            yield m.span()
            done = m.end()
        at = text.find("@", max(at + 1, done))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    found = [("email", *s) for s in _emails(text)]
    if any(c in text for c in "0123456789"):
        for m in IP.finditer(text):
            if all(_octet(p) for p in _SPLIT_IP.split(m[0])):
                found.append(("ip", *m.span()))
        for m in CARD.finditer(text):
            digits = m[0].replace(" ", "").replace("-", "")
            if 14 <= len(digits) <= 19 and _luhn(digits):
                found.append(("card", *m.span()))
        if "+" in text:
            for m in PHONE.finditer(text):
                if 10 <= sum(c.isdigit() for c in m[0]) <= 15:
                    found.append(("phone", *m.span()))
    return found


# ---- tokens and their shapes, the same for training and use ----
CUES = ("tel", "phone", "call", "fax", "mobile", "mail", "email", "ip", "host", "server", "card", "visa")
MARKS = "@.-+()_%:/,#[]"
SHAPES = ("w", "T", "U", *(f"d{n}" for n in range(1, 9)), "dlong", "sp", "nl", *MARKS, "p", "^", "$", "at", "dot", *CUES)
NUMBER = {x: k for k, x in enumerate(SHAPES)}
PLAIN = ("w", "T", "U", "sp", "nl", ".", ",", "p", "-", "^", "$")  # contexts that may be settled beforehand
START, END = 0x110000, 0x110001  # stand around each text, twice, as code points of their own
LOW, UP, DIGIT, BLANK, SINGLE = range(5)  # classes of characters; from SINGLE on each is a token by itself
UNSEEN = 255


def _class(c: str) -> int:
    if c in "0123456789":
        return DIGIT
    if c == "\n":
        return SINGLE + NUMBER["nl"]
    if c.isspace():
        return BLANK
    if c.isalnum() and not c.isdecimal():
        return UP if c.isupper() else LOW
    return SINGLE + NUMBER[c if c in MARKS else "p"]


_classes = np.full(END + 1, UNSEEN, np.uint8)
_classes[START], _classes[END] = SINGLE + NUMBER["^"], SINGLE + NUMBER["$"]
_ENDS = np.zeros((128, 128), bool)  # first and last letters of the words that are shapes
for _w in ("at", "dot", *CUES):
    _ENDS[ord(_w[0]), ord(_w[-1])] = _ENDS[ord(_w[0].upper()), ord(_w[-1])] = _ENDS[ord(_w[0].upper()), ord(_w[-1].upper())] = True


def _points(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all texts in a row with START and END around each; where each text begins."""
    around = (np.array([START, START], np.uint32), np.array([END, END], np.uint32))
    own = [np.frombuffer(t.encode("utf-32-le", "surrogatepass"), "<u4") for t in texts]
    size = np.array([len(x) + 4 for x in own], np.int64)
    return np.concatenate([y for x in own for y in (around[0], x, around[1])]), np.cumsum(size) - size + 2


def tokens(points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(starts, shapes): runs of letters, digits and white space but line ends, else single characters."""
    cls = _classes[points]
    if (cls == UNSEEN).any():
        for u in np.unique(points[cls == UNSEEN]).tolist():
            _classes[u] = _class(chr(u))
        cls = _classes[points]
    kind = np.where(cls == UP, LOW, cls)
    begins = np.r_[True, (kind[1:] != kind[:-1]) | (kind[1:] >= SINGLE)]
    starts = np.flatnonzero(begins)
    size = np.diff(np.r_[starts, len(points)])
    first = cls[starts]
    shape = np.where(first >= SINGLE, first.astype(np.int16) - SINGLE, np.where(first == BLANK, NUMBER["sp"], NUMBER["w"])).astype(np.int16)
    digits = first == DIGIT
    shape[digits] = np.where(size[digits] < 13, NUMBER["d1"] - 1 + np.minimum(size[digits], 8), NUMBER["dlong"])
    capital = np.flatnonzero(first == UP)
    shape[capital] = NUMBER["T"]
    uppers = np.r_[0, np.cumsum(cls == UP)]
    shape[capital[uppers[starts[capital] + size[capital]] - uppers[starts[capital]] == size[capital]]] = NUMBER["U"]
    words = np.flatnonzero((first <= UP) & (size >= 2) & (size <= 6))
    a, z = points[starts[words]], points[starts[words] + size[words] - 1]
    words = words[_ENDS[np.minimum(a, 127), np.minimum(z, 127)] & (a < 128) & (z < 128)]
    for k, at, n in zip(words.tolist(), starts[words].tolist(), size[words].tolist()):
        word = points[at : at + n].astype("<u4").tobytes().decode("utf-32-le", "surrogatepass")
        if word in ("at", "dot") or word.lower() in CUES:
            shape[k] = NUMBER[word.lower()]
    return starts, shape


def labelled_table(n: int = 700, seed: int = 7) -> list[list[tuple[str, str]]]:
    """Small training table: rows of (text, label) pieces built by rule; no real person's data."""
    r = random.Random(seed)
    num = lambda k: "".join(r.choice("0123456789") for _ in range(k))
    name = lambda: "".join(r.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(r.randint(3, 9)))
    prose = lambda by: by.join(name() for _ in range(r.randint(3, 9)))
    plain = [
        lambda: name(), lambda: name().title(), lambda: name().upper() + "!!", lambda: name() + ",", lambda: name() + ".\n", lambda: str(r.randint(1, 3000)), lambda: f"{num(2)}.{num(2)}.{r.randint(1990, 2030)}",
        lambda: f"version {r.randint(1, 9)}.{r.randint(0, 20)}", lambda: f"{num(1)}.{num(1)}.{num(1)}", lambda: f"{r.randint(1990, 2030)}-0{r.randint(1, 9)}-{num(2)}", lambda: f"{num(2)}:{num(2)}", lambda: f"({r.randint(1, 99)})", lambda: f"$ {num(4)},{num(2)}", lambda: f"{num(3)}%",
        lambda: name() + num(2), lambda: hashlib.sha1(num(6).encode()).hexdigest(), lambda: f"{name()} at {name()}", lambda: f"@{name()}", lambda: name() + "|", lambda: "dot " + name(), lambda: num(r.randint(5, 25)), lambda: f"{num(3)}-{num(2)}",
        *[lambda: prose(" ") + ".", lambda: prose(" ").capitalize(), lambda: prose(", "), lambda: f"{prose(' ')} at {prose(' ')}"] * 2,
    ]
    real = [
        ("email", lambda: f"{name()}.{name()}@{name()}.com"), ("email", lambda: f"{name()}{num(2)}@{name()}{num(1)}.{name()}.org"), ("email", lambda: f"{name()} [at] {name()} [dot] com"), ("email", lambda: f"{name()} (at) {name()} (dot) org"), ("email", lambda: f"{name()} @ {name()}.net"),
        ("phone", lambda: f"+{num(1)} ({num(3)}) {num(3)}-{num(4)}"), ("phone", lambda: f"({num(3)}) {num(3)}-{num(4)}"), ("phone", lambda: f"+{num(2)} {num(3)} {num(7)}"), ("phone", lambda: f"{num(3)}-{num(3)}-{num(4)}"), ("phone", lambda: f"{num(3)}.{num(3)}.{num(4)}"), ("phone", lambda: f"{num(3)} {num(3)} {num(4)}"),
        ("ip", lambda: ".".join(str(r.randint(0, 255)) for _ in range(4))), ("ip", lambda: "[.]".join(str(r.randint(0, 255)) for _ in range(4))), ("card", lambda: num(16)), ("card", lambda: " ".join(num(4) for _ in range(4))), ("card", lambda: "-".join(num(4) for _ in range(4))),
    ]
    cue = {"phone": ["tel: ", "phone ", "call "], "email": ["mail: ", "email "], "ip": ["ip ", "host: "], "card": ["card ", "visa: "]}
    rows = []
    for _ in range(n):
        row: list[tuple[str, str]] = []
        for _ in range(r.randint(3, 9)):
            if r.random() < 0.35:
                kind, make = r.choice(real)
                if r.random() < 0.3:
                    row.append((r.choice(cue[kind]), "o"))
                row.append((make(), kind))
            else:
                row.append((r.choice(plain)(), "o"))
            row.append((r.choice([" ", " ", ", ", ". ", ".\n", "### ", " | "]), "o"))
        rows.append(row)
    return rows


def labelled_tokens(rows: list[list[tuple[str, str]]]) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Shapes (with the marks around a text) and label numbers (of the tokens of the text) of each row."""
    shapes, labels = [], []
    for row in rows:
        points, _ = _points(["".join(t for t, _ in row)])
        starts, shape = tokens(points)
        of_point = np.repeat([LABELS.index(y) for _, y in row], [len(t) for t, _ in row])
        shapes.append(shape)
        labels.append(of_point[starts[2:-2] - 2])
    return shapes, labels


K, S = len(LABELS), len(SHAPES)
TEMPLATES = ((0,), (-1, 0), (0, 1), (-1, 0, 1), (-2, -1, 0), (0, 1, 2))  # neighbours whose shapes make a feature
LEAD = 1.0  # by which "other" leads in a sure context
CELLS = 60_000  # tokens of runs, with padding, that are decoded at once


class Field:
    """Weights of state features, a table for each template, and of transitions."""

    def __init__(self, state: list[np.ndarray], move: np.ndarray):
        self.state, self.move = state, move
        self.plain = np.full(S, len(PLAIN), np.int32)
        self.plain[[NUMBER[x] for x in PLAIN]] = np.arange(len(PLAIN))
        self.sure, self.depth = self._sure()

    @staticmethod
    def _features(shape: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
        """For each template the feature's number of each token."""
        out = []
        for template in TEMPLATES:
            f = np.zeros(len(at), np.int64)
            for d in template:
                f = f * S + shape[at + d]
            out.append(f)
        return out

    def scores(self, shape: np.ndarray, at: np.ndarray) -> np.ndarray:
        return sum(table[f] for table, f in zip(self.state, self._features(shape, at)))

    def _sure(self) -> tuple[np.ndarray, int]:
        """Of each context of five plain shapes: does "other" lead by LEAD even inside a run of another label?
        And how many such tokens on either side settle that one between them is "other".

        Were a best path to leave "other" in a stretch of such tokens, taking "other" there instead would
        gain LEAD a token and lose at most ``turn`` where the stretch is entered and left.
        """
        n, move = len(PLAIN), self.move
        number = np.array([NUMBER[x] for x in PLAIN])
        grid = number[np.stack(np.unravel_index(np.arange(n**5), (n,) * 5), 1)]
        score = self.scores(grid.ravel(), np.arange(n**5) * 5 + 2)
        inside = max(0.0, float((move[1:, 1:] - move[0, 0]).max()))
        turn = max(0.0, float((move[1:, 1:] - move[1:, :1]).max()), float((move[1:, 1:] - move[:1, 1:]).max()))
        alone = 2 * move[0, 0] - move[0, 1:].max() - move[1:, 0].max()  # a stay between two of "other" must not gain
        sure = (score[:, :1] - score[:, 1:] > inside + LEAD).all(1) & (alone >= 0)
        sure &= ~np.isin(grid[:, 2], [NUMBER["^"], NUMBER["$"]])
        table = np.zeros((n + 1,) * 5, bool)
        table[(slice(0, n),) * 5] = sure.reshape((n,) * 5)
        return table.ravel(), int(turn / LEAD) + 2

    def open_tokens(self, shape: np.ndarray) -> np.ndarray:
        """Positions of the tokens that aren't settled; the marks around texts are none."""
        code, base = self.plain[shape], len(PLAIN) + 1
        context = code[:-4]
        for d in range(1, 5):
            context = context * base + code[d : len(code) - 4 + d]
        doubt = np.r_[0, np.cumsum(np.r_[True, True, ~self.sure[context], True, True])]
        at = np.arange(len(shape))
        near = doubt[np.minimum(at + self.depth, len(shape))] > doubt[np.maximum(at - self.depth + 1, 0)]
        return np.flatnonzero(near & (shape != NUMBER["^"]) & (shape != NUMBER["$"]))

    @classmethod
    def fit(cls, rows: list[list[tuple[str, str]]], rounds: int = 80, decay: float = 2e-4) -> Field:
        """Gradient of the log-likelihood by forward-backward, all runs at once; Adam steps."""
        shapes, gold = labelled_tokens(rows)
        size = np.array([len(g) for g in gold])
        line = np.concatenate(shapes)
        at = np.flatnonzero((line != NUMBER["^"]) & (line != NUMBER["$"]))
        # features that occur, numbered over all templates
        wide = np.stack(cls._features(line, at), 1) + np.cumsum([0, *(S ** len(t) for t in TEMPLATES)])[:-1]
        names, flat = np.unique(wide, return_inverse=True)
        flat = flat.reshape(wide.shape)
        n, longest = len(rows), int(size.max())
        place = np.concatenate([np.arange(s) + i * longest for i, s in enumerate(size)])
        y = np.concatenate(gold)
        first = np.zeros(len(y), bool)
        first[np.cumsum(size) - size] = True
        theta = np.zeros((len(names) + K, K))
        mean, square = np.zeros_like(theta), np.zeros_like(theta)
        want = np.zeros_like(theta)
        np.add.at(want[: len(names)], flat.ravel(), np.eye(K)[np.repeat(y, flat.shape[1])])
        np.add.at(want[len(names) :], (y[:-1][~first[1:]], y[1:][~first[1:]]), 1)
        live = np.arange(longest)[None, :] < size[:, None]
        for t in range(1, rounds + 1):
            state, move = theta[: len(names)], theta[len(names) :]
            score = np.zeros((n * longest, K))
            score[place] = state[flat].sum(1)
            score = score.reshape(n, longest, K)
            e, m = np.exp(score - score.max(2, keepdims=True)), np.exp(move)
            alpha, beta = np.zeros_like(e), np.zeros_like(e)
            alpha[:, 0] = e[:, 0] / e[:, 0].sum(1, keepdims=True)
            for j in range(1, longest):
                a = (alpha[:, j - 1] @ m) * e[:, j]
                alpha[:, j] = a / a.sum(1, keepdims=True)
            beta[np.arange(n), size - 1] = 1
            for j in range(longest - 2, -1, -1):
                b = (beta[:, j + 1] * e[:, j + 1]) @ m.T
                b /= np.maximum(b.sum(1, keepdims=True), 1e-300)
                beta[:, j] = np.where((j < size - 1)[:, None], b, beta[:, j])
            post = alpha * beta
            post /= np.maximum(post.sum(2, keepdims=True), 1e-300)
            pair = alpha[:, :-1, :, None] * m * (e * beta)[:, 1:, None, :]
            pair /= np.maximum(pair.sum((2, 3), keepdims=True), 1e-300)
            got = np.zeros_like(theta)
            np.add.at(got[: len(names)], flat.ravel(), np.repeat(post.reshape(-1, K)[place], flat.shape[1], axis=0))
            got[len(names) :] = (pair * live[:, 1:, None, None]).sum((0, 1))
            grad = (want - got) / n - decay * theta
            mean, square = 0.9 * mean + 0.1 * grad, 0.99 * square + 0.01 * grad**2
            theta = theta + 0.15 * (mean / (1 - 0.9**t)) / (np.sqrt(square / (1 - 0.99**t)) + 1e-8)
        tables, lo = [], 0
        for template in TEMPLATES:
            table, hi = np.zeros((S ** len(template), K)), lo + S ** len(template)
            own = (names >= lo) & (names < hi)
            table[names[own] - lo] = theta[: len(names)][own]
            tables.append(table)
            lo = hi
        return cls(tables, theta[len(names) :])

    def decode(self, shape: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Labels of the tokens at positions ``at`` (ascending) by Viterbi; all others are "other".

        Neighbouring positions form a run. Runs of like length go together, as many as fill CELLS with
        their padding, so one long run does not widen the others.
        """
        out = np.zeros(len(at), np.int8)
        if not len(at):
            return out
        score = self.scores(shape, at)
        new = np.r_[True, np.diff(at) > 1]
        begin = np.flatnonzero(new)
        size = np.diff(np.r_[begin, len(at)])
        before, after = shape[at[begin] - 1] != NUMBER["^"], shape[at[begin + size - 1] + 1] != NUMBER["$"]
        order = np.argsort(size, kind="stable")
        lo = 0
        while lo < len(order):
            hi = min(len(order), lo + max(1, CELLS // int(size[order[lo]])))
            while hi > lo + 1 and (hi - lo) * size[order[hi - 1]] > 2 * CELLS:
                hi = lo + (hi - lo) // 2
            self._viterbi(score, begin[order[lo:hi]], size[order[lo:hi]], before[order[lo:hi]], after[order[lo:hi]], out)
            lo = hi
        return out

    def _viterbi(self, score: np.ndarray, begin: np.ndarray, size: np.ndarray, before: np.ndarray, after: np.ndarray, out: np.ndarray) -> None:
        n, longest = len(begin), int(size.max())
        best = score[begin] + np.where(before[:, None], self.move[0], 0.0)
        back = np.zeros((longest, n, K), np.int8)
        for j in range(1, longest):
            live = np.flatnonzero(size > j)
            step = best[live, :, None] + self.move
            back[j, live] = step.argmax(1)
            best[live] = step.max(1) + score[begin[live] + j]
        label = (best + np.where(after[:, None], self.move[:, 0], 0.0)).argmax(1)
        for j in range(longest - 1, -1, -1):
            live = np.flatnonzero(size > j)
            out[begin[live] + j] = label[live]
            if j:
                label[live] = back[j, live, label[live]]


@lru_cache(1)
def trained_field() -> Field:
    return Field.fit(labelled_table())


def _sound(kind: str, got: str) -> bool:
    digits = "".join(c for c in got if c in "0123456789")
    if kind == "email":
        return ("@" in got or " at " in got.replace("[", " ").replace("]", " ").replace("(", " ").replace(")", " ")) and ("." in got or "dot" in got)
    if kind == "ip":
        parts = re.findall(r"[0-9]+", got)
        return len(parts) == 4 and all(len(p) <= 3 and int(p) <= 255 for p in parts)
    if kind == "card":
        return 14 <= len(digits) <= 19 and _luhn(digits)
    return 10 <= len(digits) <= 15 and len(digits) != len(got)


def _groups(texts: list[str], points: int = 1_000_000) -> Iterator[list[int]]:
    """Runs of whole texts of about so many code points."""
    run, held = [], 0
    for k, t in enumerate(texts):
        run.append(k)
        held += len(t)
        if held >= points:
            yield run
            run, held = [], 0
    if run:
        yield run


def find_spans(texts: list[str], field: Field) -> list[tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]]:
    """Base spans and added spans of each text; an added one is sound and overlaps no other span."""
    out = []
    for group in _groups(texts):
        own = [texts[k] for k in group]
        base = [base_spans(t) for t in own]
        added: list[list[tuple[str, int, int]]] = [[] for _ in own]
        points, begins = _points(own)
        starts, shape = tokens(points)
        at = field.open_tokens(shape)
        label = field.decode(shape, at)
        new = np.flatnonzero(np.r_[True, (label[1:] != label[:-1]) | (np.diff(at) > 1)]) if len(at) else at
        last = np.r_[new[1:], len(at)][: len(new)] - 1
        spans = label[new] > 0
        stops = np.r_[starts[1:], len(points)]
        los, his, kinds = starts[at[new[spans]]], stops[at[last[spans]]], label[new[spans]]
        whose = np.searchsorted(begins, los, "right") - 1
        taken: dict[int, tuple[list[int], list[int]]] = {}
        for lo, hi, kind, k in zip((los - begins[whose]).tolist(), (his - begins[whose]).tolist(), kinds.tolist(), whose.tolist()):
            got = own[k][lo:hi]
            lo, hi = lo + len(got) - len(got.lstrip()), hi - len(got) + len(got.rstrip())
            if k not in taken:
                order = sorted((a, b) for _, a, b in base[k])
                taken[k] = [a for a, _ in order], list(accumulate((b for _, b in order), max))
            firsts, reach = taken[k]
            n = bisect_left(firsts, hi)  # base spans that begin before the end; do they reach beyond the start?
            if _sound(LABELS[kind], got.strip()) and not (n and reach[n - 1] > lo):
                added[k].append((LABELS[kind], lo, hi))
        out += zip(base, added)
    return out


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda s: (s[1], KINDS.index(s[0]), s[2])))


def redact(text: str, spans: list[tuple[str, int, int]]) -> str:
    """Each maximal covered stretch becomes the name of its first span's kind in brackets."""
    out, at = [], 0
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= at:
            out += [text[at:a], f"[{kind}]"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def personal_data(field: Field):
    """A column function: text -> struct of base span counts, their digest, all spans, and the text without them.

    A null text counts as empty: no spans; ``redacted`` is null there. It reads the text alone, so other columns may
    have any names, repeated rows get repeated results and an empty table none. Time and memory are linear in a text's length.
    """

    def told(column: pd.Series) -> pd.DataFrame:
        raw = column.tolist()
        texts = [t if isinstance(t, str) else "" for t in raw]
        rows = []
        for at in range(0, len(texts), 1000):
            for t, (base, added) in zip(texts[at : at + 1000], find_spans(texts[at : at + 1000], field)):
                count = [sum(s[0] == k for s in base) for k in KINDS]
                rows.append((*count, hashlib.sha256(joined(base).encode()).hexdigest(), joined(base + added), len(base) + len(added), redact(t, base + added)))
        made = pd.DataFrame(rows, columns=["n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_spans", "redacted"])
        made["redacted"] = made["redacted"].where([isinstance(t, str) for t in raw], None)
        return made

    @F.pandas_udf("struct<n_email: bigint, n_ip: bigint, n_card: bigint, n_phone: bigint, base_sha256: string, spans: string, n_spans: bigint, redacted: string>")
    @lean
    def of(columns: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        yield from map(told, columns)

    return of


def op9_pii_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = documents(spark, sf_dir).select(F.col("doc_id").cast("long").alias("doc_id"), personal_data(trained_field())("text").alias("r"))
    return found.select("doc_id", "r.n_email", "r.n_ip", "r.n_card", "r.n_phone", "r.base_sha256", "r.spans", "r.n_spans")
