"""Licence scans with a generalised suffix automaton.

One automaton over word tokens holds every substring of all licence templates and base
phrases. A document is streamed through it: at each word the automaton gives the longest
match that ends there (the matching statistics) and a state that knows in which templates,
and where, that match stands. Maximal long matches of one template that follow each other
in both texts are chained into a covered span.

Only places where a long match can be are streamed: a match of two or more words consists
of word pairs that occur in some template, so runs of such pairs (found with array lookups)
contain every match, and the automaton starts afresh at each run. This is exact.

Edge cases: null and empty texts give zero words, no labels and score 0; repeated rows and
repeated ids give a row each; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections import defaultdict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from . import store, textops
from .license_texts import BASE_PHRASES, TEMPLATES

_SPAN = store.schema("label string, first_word long, last_word long, coverage double")
SCHEMA = store.schema(
    "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double",
    spans=T.ArrayType(_SPAN),
)


class SuffixAutomaton:
    """Generalised suffix automaton of token sequences."""

    def __init__(self) -> None:
        self.next: list[dict[int, int]] = [{}]
        self.link: list[int] = [-1]
        self.length: list[int] = [0]
        #: per state: sequence -> least end position of the state's substrings there
        self.ends: list[dict[int, int]] = [{}]

    def _state(self, length: int, edges: dict[int, int], link: int) -> int:
        self.next.append(edges)
        self.length.append(length)
        self.link.append(link)
        self.ends.append({})
        return len(self.next) - 1

    def _split(self, parent: int, token: int, child: int) -> int:
        """A state of its own for the substrings of ``child`` that ``parent`` can reach."""
        twin = self._state(self.length[parent] + 1, dict(self.next[child]), self.link[child])
        self.link[child] = twin
        while parent >= 0 and self.next[parent].get(token) == child:
            self.next[parent][token] = twin
            parent = self.link[parent]
        return twin

    def add(self, sequence: int, tokens: list[int]) -> None:
        last = 0
        for at, token in enumerate(tokens):
            last = self._append(last, token)
            self.ends[last].setdefault(sequence, at)

    def _append(self, last: int, token: int) -> int:
        there = self.next[last].get(token)
        if there is not None:
            return there if self.length[there] == self.length[last] + 1 else self._split(last, token, there)
        new = self._state(self.length[last] + 1, {}, 0)
        p = last
        while p >= 0 and token not in self.next[p]:
            self.next[p][token] = new
            p = self.link[p]
        if p >= 0:
            q = self.next[p][token]
            self.link[new] = q if self.length[q] == self.length[p] + 1 else self._split(p, token, q)
        return new

    def close(self) -> None:
        """Hand end positions down the suffix links, longest states first."""
        for v in sorted(range(1, len(self.next)), key=lambda v: -self.length[v]):
            up = self.ends[self.link[v]]
            for sequence, at in self.ends[v].items():
                up[sequence] = min(at, up.get(sequence, at))

    def stream(self, tokens: list[int]) -> list[tuple[int, int]]:
        """(state, matched length) after each token."""
        v, n, out = 0, 0, []
        for token in tokens:
            while v and token not in self.next[v]:
                v = self.link[v]
                n = self.length[v]
            if token in self.next[v]:
                v, n = self.next[v][token], n + 1
            else:
                v, n = 0, 0
            out.append((v, n))
        return out


@dataclass(frozen=True)
class ScanSpec:
    templates: tuple = tuple(TEMPLATES)
    phrases: tuple = tuple(BASE_PHRASES.items())
    min_match: int = 4  # words of a match that can enter a chain
    max_gap: int = 12  # words between two chained matches
    min_cover: float = 0.6  # of a template's words, or
    min_words: int = 16  # as many covered words, for a label


def _tokens(text: str) -> list[bytes]:
    return re.findall(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", text.lower().encode())


class Scanner:
    def __init__(self, spec: ScanSpec) -> None:
        self.spec = spec
        texts = [(label, _tokens(text)) for label, text in spec.templates] + [(label, _tokens(text)) for text, label in spec.phrases]
        self.label = [label for label, _ in texts]
        self.size = [len(t) for _, t in texts]
        self.base_from = len(spec.templates)
        vocabulary = sorted({w for _, t in texts for w in t})
        data = np.frombuffer(b"".join(vocabulary), np.uint8)
        ends = np.cumsum([len(w) for w in vocabulary])
        hashes = textops.word_hashes(data, np.concatenate([[0], ends[:-1]]), ends)
        order = np.argsort(hashes)
        self.hashes = hashes[order]
        number = {vocabulary[j]: i for i, j in enumerate(order)}
        self.n = len(vocabulary)
        self.automaton = SuffixAutomaton()
        self.pair = np.zeros((self.n + 1, self.n + 1), bool)
        self.base_pair = np.zeros_like(self.pair)
        for k, (_, t) in enumerate(texts):
            ids = [number[w] for w in t]
            self.automaton.add(k, ids)
            self.pair[ids[:-1], ids[1:]] = True
            if k >= self.base_from:
                self.base_pair[ids[:-1], ids[1:]] = True
        self.automaton.close()
        a = self.automaton
        #: states whose longest string ends with a base phrase, with the longest such phrases
        self.base_ends: list[list[int]] = [[] for _ in a.next]
        for v in sorted(range(1, len(a.next)), key=lambda v: a.length[v]):
            here = [k for k in range(self.base_from, len(texts)) if a.ends[v].get(k) == self.size[k] - 1 and a.length[v] >= self.size[k] > a.length[a.link[v]]]
            self.base_ends[v] = here + self.base_ends[a.link[v]]

    def ids(self, hashes: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.hashes, hashes), self.n - 1)
        return np.where(self.hashes[at] == hashes, at, self.n)

    def regions(self, ids: np.ndarray, ptr: np.ndarray) -> list[tuple[int, int]]:
        """Word runs of one document each that contain every match worth looking at."""
        if len(ids) < 2:
            return []
        ok = textops.in_document(ptr, len(ids) - 1, 2)
        hit = self.pair[ids[:-1], ids[1:]] & ok
        base = np.concatenate([[0], np.cumsum(self.base_pair[ids[:-1], ids[1:]] & ok)])
        lo, hi = textops.runs(hit)
        keep = (hi - lo + 1 >= self.spec.min_match) | (base[hi] > base[lo])
        return list(zip(lo[keep].tolist(), (hi[keep] + 1).tolist(), strict=True))

    def document(self, regions: list[tuple[int, list[int]]]) -> tuple[list[tuple[int, str]], list[tuple]]:
        """Base places (first word, label) and chained spans of one document."""
        a, spec = self.automaton, self.spec
        base: list[tuple[int, str]] = []
        matches: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
        for start, ids in regions:
            states = a.stream(ids)
            for i, (v, n) in enumerate(states):
                for k in self.base_ends[v]:
                    if self.size[k] <= n:
                        base.append((start + i - self.size[k] + 1, self.label[k]))
                grows = i + 1 < len(states) and states[i + 1][1] == n + 1
                if n >= spec.min_match and not grows:
                    for k, end in a.ends[v].items():
                        if k < self.base_from:
                            matches[k].append((start + i + 1 - n, n, end + 1 - n))
        spans = []
        for k, found in matches.items():
            spans += self._chains(k, sorted(found))
        return base, sorted(spans, key=lambda s: (s[1], -s[2], s[0]))

    def _chains(self, k: int, found: list[tuple[int, int, int]]) -> list[tuple]:
        """Join matches of template k that follow each other in document and template."""
        out, chain = [], []

        def finish() -> None:
            if chain:
                covered = sum(n for _, n, _ in chain)
                share = min(1.0, covered / self.size[k])
                if share >= self.spec.min_cover or covered >= self.spec.min_words:
                    out.append((self.label[k], chain[0][0], chain[-1][0] + chain[-1][1] - 1, share))

        for at, n, template in found:
            if chain:
                last_at, last_n, last_t = chain[-1]
                overlap = max(0, last_at + last_n - at)
                at, n, template = at + overlap, n - overlap, template + overlap
                if n <= 0:
                    continue
                if at - last_at - last_n > self.spec.max_gap or template < last_t + last_n:
                    finish()
                    chain = []
            chain.append((at, n, template))
        finish()
        return out


def scan(docs: DataFrame, spec: ScanSpec = ScanSpec()) -> DataFrame:
    """One row per document: base places, labels, confidence and template spans.

    ``score`` is the largest share of a template covered by one chain, or 1 where a base
    phrase stands in full; 0 without either."""

    def run(batches):
        scanner = Scanner(spec)
        for batch, data, offsets in textops.blocks(batches):
            data = textops.lower(data)
            starts, ends, ptr = textops.words(data, offsets, textops.ALNUM)
            ids = scanner.ids(textops.word_hashes(data, starts, ends))
            n = batch.num_rows
            by_doc: dict[int, list] = defaultdict(list)
            for lo, hi in scanner.regions(ids, ptr):
                d = int(np.searchsorted(ptr, lo, "right")) - 1
                by_doc[d].append((lo - int(ptr[d]), ids[lo:hi].tolist()))
            out = {k: [None] * n for k in ("first_word", "last_word")} | {k: [""] * n for k in ("base_labels", "labels")}
            out |= {"n_base": [0] * n, "score": [0.0] * n, "spans": [[] for _ in range(n)]}
            for d, regions in by_doc.items():
                base, spans = scanner.document(regions)
                if base:
                    out["n_base"][d], out["first_word"][d], out["last_word"][d] = len(base), min(base)[0], max(base)[0]
                    out["base_labels"][d] = ",".join(sorted({x for _, x in base}))
                out["labels"][d] = ",".join(sorted({x for _, x in base} | {s[0] for s in spans}))
                out["score"][d] = max([1.0 if base else 0.0, *(s[3] for s in spans)])
                out["spans"][d] = [dict(zip(("label", "first_word", "last_word", "coverage"), s, strict=True)) for s in spans]
            yield store.rows(SCHEMA, doc_id=batch.column(0), n_words=pa.array(np.diff(ptr)), **out)

    return store.documents(docs, "doc_id", "text").mapInArrow(run, SCHEMA)
