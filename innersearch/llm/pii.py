"""Personal data: patterns with checks, and a linear-chain conditional random field over word shapes.

The patterns give the base spans.  Around every word that holds a digit or '@' the field reads the
sequence of such words (neighbouring ones form one sequence, all others are plain context), sees the
shape of each word and of the words beside it, and labels it; the sequences of a slice of texts are decoded
together by Viterbi in numpy.  Spans it finds are added where no base span lies, if they pass the
same checks (Luhn, parts up to 255, number of digits) for their kind.  It is trained on the small labelled table
of `labelled_table`, made from a seed.

Defined cases: null and empty texts have no spans; positions are code points, end exclusive; repeated
documents are rows of their own; an empty table gives no rows; other columns are ignored.
Every step is linear in the text, also on one endless word."""

from __future__ import annotations

import functools
import random
import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from innersearch.llm.common import annotate

KINDS = ("email", "ip", "card", "phone")
LABELS = ("O", *(f"{p}-{k}" for k in KINDS for p in ("B", "I")))

_LOCAL = re.compile(r"[A-Za-z0-9._%+-]+")
_HOST = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_HINT = re.compile(r"[0-9@]")
_SPACE = re.compile(r"[\x20\x09-\x0D]")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = ord(d) - 48
        total += n if i % 2 == 0 else n * 2 - 9 * (n > 4)
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join([c for c in s if "0" <= c <= "9"])


def passes(kind: str, s: str) -> bool:
    if kind == "ip":
        return all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in s.split("."))
    if kind == "card":
        d = _digits(s)
        return 14 <= len(d) <= 19 and luhn(d)
    return 10 <= len(_digits(s)) <= 15 if kind == "phone" else True


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost non-overlapping addresses; each '@' is looked at once."""
    out, end, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in _LOCAL_CHARS:
            start -= 1
        host = _HOST.match(text, at + 1) if start < at else None
        if host:
            end = host.end()
            out.append((start, end))
            at = text.find("@", end)
        else:
            end = max(end, at + 1)
            at = text.find("@", at + 1)
    return out


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the patterns, ordered by start and then kind."""
    if not _HINT.search(text):
        return []
    found = [(s, e, 0) for s, e in emails(text)]
    for k, pattern in ((1, _IP), (2, _CARD), (3, _PHONE)):
        found += [(m.start(), m.end(), k) for m in pattern.finditer(text) if passes(KINDS[k], m.group())]
    return [(s, e, KINDS[k]) for s, e, k in sorted(found, key=lambda x: (x[0], x[2]))]


# ---- the conditional random field


@functools.lru_cache(maxsize=50_000)
def shape(word: str) -> str:
    """Runs of letters become x, digits keep their number up to 9 as 9{n}, other characters stay."""
    word = word[:64]
    word = re.sub(r"[^\W\d_]+", "x", word)
    return re.sub(r"[0-9]+", lambda m: f"9{{{min(len(m.group()), 9)}}}", word)


def features(words: list[str], left: str, right: str) -> list[list[str]]:
    """Features of each word of a sequence; left and right stand for what is beside it ('w' or '^')."""
    shapes = [left, *[shape(w) for w in words], right]
    return [[f"0{shapes[i]}", f"-{shapes[i - 1]}", f"+{shapes[i + 1]}", f"=0{re.sub(r'[{][0-9][}]', '', shapes[i])}", f"2{shapes[i - 1]} {shapes[i]}", f"3{shapes[i]} {shapes[i + 1]}"] for i in range(1, len(shapes) - 1)]


def labelled_table(n: int = 600, seed: int = 5) -> list[tuple[list[str], list[str], str, str]]:
    """The labelled rows: (words, labels, left, right), generated from rules and a seed."""
    r = random.Random(seed)
    num = lambda k: "".join(r.choice("0123456789") for _ in range(k))
    tail = lambda: r.choice(["", "", "", ".", ",", ";", ")"])
    name = lambda: "".join(r.choice("abcdefgh") for _ in range(r.randint(2, 7)))

    def one() -> tuple[list[str], str]:
        kind = r.choice(["email", "ip", "card", "card", "phone", "phone", "phone", "O", "O", "O", "O"])
        if kind == "email":
            return [f"{name()}{r.choice(['', '.' + num(2), num(1)])}@{name()}{num(1)}.{name()}.com{tail()}"], kind
        if kind == "ip":
            return [".".join(num(r.randint(1, 3)) for _ in range(4)) + tail()], kind
        if kind == "card":
            return r.choice([[num(16) + tail()], [num(15) + tail()], ["-".join(num(4) for _ in range(4)) + tail()], [num(4), num(4), num(4), num(4) + tail()]]), kind
        if kind == "phone":
            return r.choice(
                [
                    [f"({num(3)})", f"{num(3)}-{num(4)}{tail()}"],
                    [f"({num(3)})", f"{num(3)}-{num(4)}{tail()}"],
                    [f"{num(3)}-{num(3)}-{num(4)}{tail()}"],
                    [f"{num(3)}.{num(3)}.{num(4)}{tail()}"],
                    [f"({num(3)}){num(3)}-{num(4)}{tail()}"],
                    [f"+{num(1)}", f"({num(3)})", f"{num(3)}-{num(4)}{tail()}"],
                    [f"+{num(2)}", num(3), num(3), num(4) + tail()],
                    [f"+{num(1)}-{num(3)}-{num(3)}-{num(4)}{tail()}"],
                    [f"1-{num(3)}-{num(3)}-{num(4)}{tail()}"],
                ]
            ), kind
        return r.choice(
            [
                [num(r.randint(1, 5)) + tail()],
                [f"({num(r.randint(1, 4))})"],
                [f"{num(4)}-{num(2)}-{num(2)}"],
                [f"{num(2)}:{num(2)}"],
                [f"{num(r.randint(1, 3))}.{num(r.randint(1, 4))}{tail()}"],
                [f"v{num(1)}.{num(1)}.{num(1)}"],
                [f"{name()}={num(3)}{name()}{num(4)}"],
                [f"${num(3)},{num(3)}"],
                [f"{num(3)}-{num(4)}"],
                [f"{num(1)}."],
                [f"@{name()}"],
                [f"{name().upper()}{num(2)}{name().upper()}"],
                [f"{num(9)}{num(12)}"],
                [f"{num(3)}%"],
            ]
        ), "O"

    rows = []
    for _ in range(n):
        words, labels = [], []
        for _ in range(r.choice([1, 1, 1, 2, 3])):
            w, kind = one()
            words += w
            labels += ["O"] * len(w) if kind == "O" else [f"{'I' if i else 'B'}-{kind}" for i in range(len(w))]
        rows.append((words, labels, r.choice("www^"), r.choice("www^")))
    return rows


class Field:
    """A trained linear-chain field: feature weights, transition weights, start weights."""

    def __init__(self, rows, steps: int = 80, rate: float = 0.3, decay: float = 1e-3):
        self.index: dict[str, int] = {}
        data = []
        for words, labels, left, right in rows:
            data.append(([[self.index.setdefault(f, len(self.index)) for f in fs] for fs in features(words, left, right)], [LABELS.index(y) for y in labels]))
        k, n, t = len(LABELS), len(data), max(len(y) for _, y in data)
        width = 6
        x = np.full((n, t, width), len(self.index), np.int64)
        y, real = np.zeros((n, t), np.int64), np.zeros((n, t), bool)
        for i, (fs, ys) in enumerate(data):
            x[i, : len(fs)], y[i, : len(ys)], real[i, : len(ys)] = fs, ys, True
        params = [np.zeros((len(self.index) + 1, k)), np.zeros((k, k)), np.zeros(k)]
        moments = [(np.zeros_like(p), np.zeros_like(p)) for p in params]
        for step in range(1, steps + 1):
            for p, g, (m, v) in zip(params, self._gradient(params, x, y, real, decay), moments, strict=True):
                m += 0.1 * (g - m)
                v += 0.01 * (g * g - v)
                p += rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
            params[0][-1] = 0
        self.emit, self.trans, self.start = params

    @staticmethod
    def _gradient(params, x, y, real, decay):
        """Gradient of the mean log-likelihood by forward-backward over all sequences at once."""
        emit, trans, start = params
        n, t, _ = x.shape
        k = len(start)
        e = emit[x].sum(2)
        lse = lambda a, axis: (m := a.max(axis, keepdims=True)).squeeze(axis) + np.log(np.exp(a - m).sum(axis))
        fwd, bwd = np.zeros((n, t, k)), np.zeros((n, t, k))
        fwd[:, 0] = e[:, 0] + start
        for i in range(1, t):
            nxt = lse(fwd[:, i - 1, :, None] + trans, 1) + e[:, i]
            fwd[:, i] = np.where(real[:, i, None], nxt, fwd[:, i - 1])
        z = lse(fwd[:, -1], 1)
        for i in range(t - 2, -1, -1):
            nxt = lse(trans + (e[:, i + 1] + bwd[:, i + 1])[:, None, :], 2)
            bwd[:, i] = np.where(real[:, i + 1, None], nxt, 0)
        post = np.exp(fwd + bwd - z[:, None, None]) * real[:, :, None]
        gold = np.eye(k)[y] * real[:, :, None]
        g_emit, g_trans = np.zeros_like(emit), np.zeros_like(trans)
        for j in range(x.shape[2]):
            np.add.at(g_emit, x[:, :, j].ravel(), (gold - post).reshape(-1, k))
        for i in range(1, t):
            both = real[:, i]
            p = np.exp(fwd[both, i - 1, :, None] + trans + (e[both, i] + bwd[both, i])[:, None, :] - z[both, None, None])
            g_trans += gold[both, i - 1].T @ gold[both, i] - p.sum(0)
        g_start = (gold[:, 0] - post[:, 0]).sum(0)
        return [g / n - decay * p for g, p in zip((g_emit, g_trans, g_start), params, strict=True)]

    def scores(self, seq: tuple[list[str], str, str]) -> np.ndarray:
        none = len(self.index)
        return self.emit[np.array([[self.index.get(f, none) for f in fs] for fs in features(*seq)])].sum(1)

    def decode(self, sequences: list[tuple[list[str], str, str]]) -> list[list[str]]:
        """Best labels of each sequence: Viterbi over batches of sequences of similar length."""
        out: list[list[str]] = [[] for _ in sequences]
        groups: dict[int, list[int]] = {}
        for i, s in enumerate(sequences):
            groups.setdefault(len(s[0]).bit_length(), []).append(i)
        for members in groups.values():
            for at in range(0, len(members), 4096):
                some = members[at : at + 4096]
                es = [self.scores(sequences[i]) for i in some]
                t, k = max(len(e) for e in es), len(self.start)
                e, ns = np.zeros((len(es), t, k)), np.array([len(x) for x in es])
                for j, x in enumerate(es):
                    e[j, : len(x)] = x
                best, back = e[:, 0] + self.start, np.zeros((len(es), t, k), np.int8)
                for i in range(1, t):
                    all_ = best[:, :, None] + self.trans
                    live = (i < ns)[:, None]
                    back[:, i] = np.where(live, all_.argmax(1), np.arange(k))
                    best = np.where(live, all_.max(1) + e[:, i], best)
                label = best.argmax(1)
                path = np.zeros((len(es), t), np.int64)
                for i in range(t - 1, -1, -1):
                    path[:, i] = label
                    label = back[np.arange(len(es)), i, label]
                for j, i in enumerate(some):
                    out[i] = [LABELS[y] for y in path[j, : ns[j]]]
        return out


@functools.lru_cache(maxsize=1)
def trained_field() -> Field:
    return Field(labelled_table())


def sequences_of(text: str) -> list[tuple[list[tuple[int, int]], str, str]]:
    """Runs of neighbouring words with a digit or '@': their places, and what is beside each run."""
    words, end = [], 0
    hint = _HINT.search(text)
    while hint:
        p = hint.start()
        start = max(text.rfind(c, end, p) for c in " \t\n\x0b\x0c\r") + 1
        start = max(start, end)
        stop = _SPACE.search(text, p)
        new_end = stop.start() if stop else len(text)
        words.append((start, new_end))
        end = new_end
        hint = _HINT.search(text, end)
    runs: list[list[tuple[int, int]]] = []
    for s, e in words:
        if runs and s - runs[-1][-1][1] <= 2 and not text[runs[-1][-1][1] : s].strip(" "):
            runs[-1].append((s, e))
        else:
            runs.append([(s, e)])
    return [(run, "^" if not run[0][0] or text[run[0][0] - 1] == "\n" else "w", "^" if run[-1][1] >= len(text) or text[run[-1][1]] == "\n" else "w") for run in runs]


_OPEN, _CLOSE = "\"'<[{,;:", "\"'>]}.,;:!?"


def field_spans(field: Field, texts: list[str]) -> list[list[tuple[int, int, str]]]:
    found = [sequences_of(t) for t in texts]
    flat = [([texts[i][s:e] for s, e in run], left, right) for i, seqs in enumerate(found) for run, left, right in seqs]
    labels = iter(field.decode(flat))
    out = []
    for text, seqs in zip(texts, found, strict=True):
        spans: list[tuple[int, int, str]] = []
        for run, _, _ in seqs:
            open_ = None
            for (s, e), y in zip(run, next(labels), strict=True):
                kind = y[2:]
                if y[0] == "I" and open_ and open_[2] == kind:
                    open_ = (open_[0], e, kind)
                    continue
                if open_:
                    spans.append(open_)
                open_ = (s, e, kind) if kind else None
            if open_:
                spans.append(open_)
        tidy = []
        for s, e, kind in spans:
            while s < e and text[s] in _OPEN:
                s += 1
            while s < e and text[e - 1] in _CLOSE:
                e -= 1
            if s < e and text[e - 1] == ")" and text.count("(", s, e) < text.count(")", s, e):
                e -= 1
            ok = _EXACT[kind].fullmatch(text, s, e) and passes(kind, text[s:e])
            if ok:
                tidy.append((s, e, kind))
        out.append(tidy)
    return out


#: What an added span must look like as a whole.
_EXACT = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
    "ip": re.compile(r"[0-9]+(\.[0-9]+){3}"),
    "card": re.compile(r"[0-9](?:[\x20-]?[0-9])+"),
    "phone": re.compile(r"\+?[(0-9][\x20().0-9-]+[0-9]"),
}


def all_spans(field: Field, texts: list[str]) -> list[tuple[list, list]]:
    """For each text its base spans, and all spans in order."""
    out = []
    for text, more in zip(texts, field_spans(field, texts), strict=True):
        base = base_spans(text)
        free = [x for x in more if all(x[1] <= s or e <= x[0] for s, e, _ in base)]
        out.append((base, sorted(base + free, key=lambda x: (x[0], KINDS.index(x[2])))))
    return out


def written(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, e, k in spans)


def find_pii(docs: DataFrame, keep: list[str], field: Field | None = None) -> DataFrame:
    """Columns `keep` with base (string), spans (string) and the base counts of each kind."""
    shared = docs.sparkSession.sparkContext.broadcast(field or trained_field())

    def make():
        model = shared.value

        def work(texts):
            got = all_spans(model, [t.decode() if t else "" for t in texts])
            return [[written(b) for b, _ in got], [written(a) for _, a in got], *[[sum(x[2] == k for x in b) for b, _ in got] for k in KINDS]]

        return work

    return annotate(docs, keep, "base string, spans string, " + ", ".join(f"n_{k} long" for k in KINDS), make)


def redact(docs: DataFrame, field: Field | None = None) -> DataFrame:
    """docs with every span of its texts replaced by its kind in angle brackets."""
    shared = docs.sparkSession.sparkContext.broadcast(field or trained_field())
    others = [c for c in docs.columns if c != "text"]

    def make():
        model = shared.value

        def work(texts):
            out = []
            for raw, (_, spans) in zip(texts, all_spans(model, [t.decode() if t else "" for t in texts]), strict=True):
                text, parts, at = raw.decode() if raw else "", [], 0
                for s, e, k in spans:
                    if s >= at:
                        parts += [text[at:s], f"<{k}>"]
                        at = e
                out.append(None if raw is None else "".join([*parts, text[at:]]))
            return [out]

        return work

    return annotate(docs, others, "__redacted string", make).withColumnRenamed("__redacted", "text").select(*[F.col(f"`{c}`") for c in docs.columns])


def pii_digest(docs: DataFrame) -> DataFrame:
    found = find_pii(docs, ["doc_id"])
    return found.select("doc_id", *[f"n_{k}" for k in KINDS], F.sha2("base", 256).alias("base_sha256"), "spans")
