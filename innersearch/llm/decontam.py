"""Benchmark decontamination with a generalised suffix automaton.

The automaton recognises every factor of the normalised items.  A document's words are streamed
through it; the longest matching length after each word tells which windows of an item end there.
Words outside the items' vocabulary reset the match, so only runs of known words are walked.

The automaton is broadcast to the workers.  One automaton holds at most about MAX_WORDS item words, some 40 MB; a larger
benchmark is divided into several, items of more words into pieces that share all windows.  The documents pass the automata one
after the other, each pass written to the shared folder, so neither the driver nor a worker ever holds more than one.

Defined cases: null and empty texts have no words and no hits; an item without words occurs nowhere; an
item of fewer words than a window is one window itself; items with one id count once; repeated
documents are rows of their own; empty tables give no rows or no hits; other columns are kept, whatever their names, or ignored."""

from __future__ import annotations

import math
import re
from array import array
from collections.abc import Iterator
from itertools import repeat

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from innersearch.llm.common import annotate, columns_of, fresh, materialize

WINDOW = 10
MAX_WORDS = 200_000

#: ASCII letters in lower case, digits and all bytes of non-ASCII characters make words.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
_WORD_BYTES = re.compile(rb"[0-9A-Za-z\x80-\xff]+")
_WORD_SQL = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def words_of(text: bytes) -> list[bytes]:
    return text.translate(_FOLD).split()


class Automaton:
    """Generalised suffix automaton over word ids with the windows and short items it must report.

    Most states have one step.  Built, the automaton keeps a word and a target for each state in flat arrays (word -1: none),
    and further steps in one table by (state, word)."""

    def __init__(self, items: list[tuple[str, bytes]], window: int = WINDOW):
        self.window = window
        self.vocab: dict[bytes, int] = {}
        self.names = sorted({name for name, _ in items})
        index = {name: i for i, name in enumerate(self.names)}
        self.step: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        sequences = []
        for name, text in items:
            seq = array("i", [self.vocab.setdefault(w, len(self.vocab)) for w in words_of(text)])
            if seq:
                sequences.append((index[name], seq))
                last = 0
                for w in seq:
                    last = self._extend(last, w)
        self._flatten()
        self.at_window: dict[int, tuple[int, ...]] = {}
        self.short: dict[int, tuple] = {}
        windows: dict[int, set[int]] = {}
        shorts: dict[int, set[tuple[int, int]]] = {}
        for item, seq in sequences:
            state = 0
            for i, w in enumerate(seq):
                state = self._to(state, w)
                if i + 1 >= window:
                    windows.setdefault(self._ancestor(state), set()).add(item)
            if len(seq) < window:
                shorts.setdefault(self._holding(state, len(seq)), set()).add((item, len(seq)))
        self.at_window = {k: tuple(v) for k, v in windows.items()}
        self.short = {k: tuple(v) for k, v in shorts.items()}
        self.least = min([window, *[len(s) for _, s in sequences]]) if sequences else 0
        self._shorts: dict[int, list] = {}

    def _flatten(self) -> None:
        self.word, self.target = array("i"), array("i")
        self.more: dict[tuple[int, int], int] = {}
        for state, steps in enumerate(self.step):
            pairs = iter(steps.items())
            w, to = next(pairs, (-1, -1))
            self.word.append(w)
            self.target.append(to)
            self.more.update({(state, x): y for x, y in pairs})
        self.link, self.length = array("i", self.link), array("i", self.length)
        del self.step

    def _to(self, state: int, w: int) -> int | None:
        return self.target[state] if self.word[state] == w else self.more.get((state, w))

    def _extend(self, last: int, w: int) -> int:
        step, link, length = self.step, self.link, self.length
        if w in step[last]:
            q = step[last][w]
            return q if length[q] == length[last] + 1 else self._split(last, w, q)
        new = len(step)
        step.append({})
        link.append(0)
        length.append(length[last] + 1)
        p = last
        while p >= 0 and w not in step[p]:
            step[p][w] = new
            p = link[p]
        if p >= 0:
            q = step[p][w]
            link[new] = q if length[q] == length[p] + 1 else self._split(p, w, q)
        return new

    def _split(self, p: int, w: int, q: int) -> int:
        clone = len(self.step)
        self.step.append(dict(self.step[q]))
        self.link.append(self.link[q])
        self.length.append(self.length[p] + 1)
        self.link[q] = clone
        while p >= 0 and self.step[p].get(w) == q:
            self.step[p][w] = clone
            p = self.link[p]
        return clone

    def _holding(self, state: int, n: int) -> int:
        """The ancestor of state (or itself) whose class has the factor of length n."""
        while self.length[self.link[state]] >= n:
            state = self.link[state]
        return state

    def _ancestor(self, state: int) -> int:
        return self._holding(state, self.window)

    def _short_at(self, state: int) -> list[tuple[int, int]]:
        found = self._shorts.get(state)
        if found is None:
            found, s = [], state
            while s > 0:
                found += self.short.get(s, ())
                s = self.link[s]
            self._shorts[state] = found
        return found

    def matches(self, run: list[int]) -> tuple[list[tuple[int, int]], set[int]]:
        """Hit ranges (start, end) within a run of known words, and the items whose windows occur."""
        word, target, more, link, length, window = self.word, self.target, self.more, self.link, self.length, self.window
        spans, items, state, n = [], set(), 0, 0
        for i, w in enumerate(run):
            to = target[state] if word[state] == w else more.get((state, w))
            while to is None and state:
                state = link[state]
                n = length[state]
                to = target[state] if word[state] == w else more.get((state, w))
            if to is None:
                n = 0
                continue
            state, n = to, n + 1
            if n >= window:
                items.update(self.at_window[self._ancestor(state)])
                if spans and spans[-1][1] >= i + 1 - window:
                    spans[-1] = (spans[-1][0], i + 1)
                else:
                    spans.append((i + 1 - window, i + 1))
            if self.short:
                for item, m in self._short_at(state):
                    if n >= m:
                        items.add(item)
                        spans.append((i + 1 - m, i + 1))
        return spans, items

    def scan(self, texts: list[bytes | None]) -> list[tuple[int, list[tuple[int, int]], set[int]]]:
        """For each text: words, hit ranges over word positions, item indices."""
        words, ns = [], []
        for t in texts:
            ws = words_of(t or b"")
            ns.append(len(ws))
            words += ws
            words.append(b" ")  # no word: matches do not cross documents
        out = [(n, [], set()) for n in ns]
        if not self.least or not words:
            return out
        ids = np.fromiter(map(self.vocab.get, words, repeat(-1)), np.int32, len(words))
        known = np.concatenate([[0], (ids >= 0).view(np.int8), [0]])
        edge = np.diff(known)
        begins, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        long_ = ends - begins >= self.least
        begins, ends = begins[long_], ends[long_]
        first = np.concatenate([[0], np.cumsum(np.array(ns) + 1)])
        docs = np.searchsorted(first, begins, "right") - 1
        for b, e, d in zip(begins.tolist(), ends.tolist(), docs.tolist(), strict=True):
            spans, items = self.matches(ids[b:e].tolist())
            shift = b - int(first[d])
            out[d][1].extend((s + shift, t + shift) for s, t in spans)
            out[d][2].update(items)
        return out


def merge(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1] = (out[-1][0], max(e, out[-1][1]))
        else:
            out.append((s, e))
    return out


def item_parts(benchmark: DataFrame, window: int, max_words: int) -> tuple[DataFrame, int]:
    """Rows (item_id, text, part) of the items, long ones in pieces that overlap by a window less a word; and the number of parts,
    each of about max_words words."""
    words = F.regexp_extract_all("text", F.lit(_WORD_SQL), F.lit(0))
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), words.alias("words")).where(F.size("words") > 0)
    at = F.explode(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("words") - (window - 1)), F.lit(max_words)))
    pieces = items.select("item_id", "words", at.alias("at")).select("item_id", F.array_join(F.slice("words", F.col("at"), max_words + window - 1), " ").alias("text"), F.least(F.size("words"), F.lit(max_words + window - 1)).alias("n"))
    total = pieces.agg(F.sum("n")).first()[0] or 0
    parts = max(1, math.ceil(total / max_words))
    return pieces.select("item_id", "text", F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)).alias("part")), parts


def automata(benchmark: DataFrame, window: int = WINDOW, max_words: int = MAX_WORDS) -> Iterator[tuple[Automaton, bool]]:
    """Automata over all items, one at a time, each of about max_words item words; and if it is the last one."""
    items, parts = item_parts(benchmark, window, max_words)
    if parts > 1:
        items = materialize(items, "items")
    for p in range(parts):
        rows = items.where(F.col("part") == p).collect()
        yield Automaton([(r["item_id"] or "", r["text"].encode()) for r in rows], window), p == parts - 1


#: What each pass adds, in order: words, flat merged word ranges, ids found, words in the ranges.
_ADDED = (("n_words", "long"), ("spans", "array<int>"), ("items", "array<string>"), ("n_hit", "long"))


def _cut(text: bytes, spans: list[int]) -> str:
    """The text without the words of the flat, merged ranges."""
    out, at, k = [], 0, 0
    for i, m in enumerate(_WORD_BYTES.finditer(text)):
        if i == spans[k]:
            out.append(text[at : m.start()])
        if i == spans[k + 1] - 1:
            at, k = m.end(), k + 2
            if k == len(spans):
                break
    return b"".join([*out, text[at:]]).decode()


def _hits(docs: DataFrame, benchmark: DataFrame, window: int, max_words: int, cut: bool) -> tuple[DataFrame, list[str]]:
    """docs with the columns of _ADDED, under the names returned; with `cut`, also the text without its hit words.

    Every automaton is one pass over the documents, and one Python worker a task does all of it."""
    sc = docs.sparkSession.sparkContext
    names = [fresh(docs.columns, n) for n, _ in _ADDED] + [fresh(docs.columns, "cut")] * cut
    added = ", ".join(f"`{n}` {t}" for n, t in zip(names, [*[t for _, t in _ADDED], "string"], strict=False))
    found = docs
    for one, last in automata(benchmark, window, max_words):
        shared = sc.broadcast(one)

        def make(shared=shared, last=last):
            auto = shared.value

            def work(texts, before=None, known=None):
                out = []
                for i, (n, sp, it) in enumerate(auto.scan(texts)):
                    old = before[i] if before else []
                    spans = merge(sp + [(old[j], old[j + 1]) for j in range(0, len(old), 2)])
                    flat = [x for s in spans for x in s]
                    row = [n, flat, sorted({*(auto.names[x] for x in it), *(known[i] if known else ())}), sum(e - s for s, e in spans)]
                    if cut:
                        row.append(None if not (last and flat) else _cut(texts[i], flat))
                    out.append(row)
                return [list(c) for c in zip(*out, strict=True)]

            return work

        found = annotate(found, docs.columns, added, make, also=() if found is docs else (names[1], names[2]))
        if not last:
            found = materialize(found, "hits")
    return found, names


def annotate_hits(docs: DataFrame, benchmark: DataFrame, keep: list[str], window: int = WINDOW, max_words: int = MAX_WORDS) -> DataFrame:
    """Columns `keep` with __n_words, __spans (flat word ranges, merged) and __items (ids found)."""
    found, names = _hits(docs.select(*[F.col(f"`{c}`") for c in dict.fromkeys([*keep, "text"])]), benchmark, window, max_words, False)
    return found.select(*[F.col(f"`{c}`") for c in (*keep, *names[:3])])


def n_hit(spans: Column) -> Column:
    """Words covered by flat ranges that may overlap."""
    ends = F.transform(F.sequence(F.lit(0), (F.size(spans) / 2 - 1).cast("int")), lambda i: F.struct(spans[(2 * i).cast("int")].alias("s"), spans[(2 * i + 1).cast("int")].alias("e")))
    step = lambda a, x: F.struct((a["n"] + F.greatest(F.lit(0), x["e"] - F.greatest(a["to"], x["s"]))).alias("n"), F.greatest(a["to"], x["e"]).alias("to"))
    return F.when(F.size(spans) == 0, F.lit(0)).otherwise(F.aggregate(F.array_sort(ends), F.struct(F.lit(0).alias("n"), F.lit(0).alias("to")), step, lambda a: a["n"])).cast("long")


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, max_coverage: float = 0.5, max_words: int = MAX_WORDS) -> DataFrame:
    """docs without the words that windows of items hit: a text loses its hit spans, and a document of
    which more than max_coverage is hit is dropped.  Documents without hits stay as they are."""
    found, (n, _, _, hit, cut) = _hits(docs, benchmark, window, max_words, True)
    kept = found.where((F.col(hit) == 0) | (F.col(hit) <= max_coverage * F.col(n)))
    return kept.withColumn("text", F.coalesce(F.col(cut), F.col("text"))).select(*columns_of(docs))


def hit_digest(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated."""
    found, (n, _, items, hit) = _hits(docs.select("doc_id", "text"), benchmark, WINDOW, MAX_WORDS, False)
    return found.select(
        "doc_id", F.col(n).alias("n_words"), F.col(hit).alias("n_hit"), F.size(items).cast("long").alias("n_items"), F.sha2(F.array_join(items, ","), 256).alias("items_sha256"), (F.col(hit) > 0).alias("contaminated")
    )
