"""Secret scanning with a trigram inverted index.

A Boolean trigram query is derived from each rule's regular expression (walking Python's parse tree). Each slice of
documents is an index segment: the positions of all trigrams that occur in some query are found in one vectorised
pass over the slice's bytes and become postings (trigram -> documents). Queries intersect and unite postings;
only the documents that remain are verified with the expression. A rule without mandatory trigrams scans all.

Segments are local to a task, so nothing is shuffled and no posting list outgrows a slice.

Defined results: a null or empty text has no span; equal rows give equal results; empty tables give empty tables;
other columns are ignored. Positions are code points, ends exclusive.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from .common import arrow_map

try:
    from re import _constants as sre
    from re import _parser as sre_parse
except ImportError:  # other Python versions keep them elsewhere
    import sre_constants as sre
    import sre_parse


@dataclass(frozen=True)
class Rule:
    """A kind of secret: its expression, the group whose length counts, and the least length of that group."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 1


# The base rules, in the order in which ties are listed.
BASE_RULES = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 16),
    Rule("hex", r"[0-9a-f]+", 0, 32),
)
# Further rules; their spans are added after the base ones.
MORE_RULES = (
    Rule("pem", r"-----BEGIN [A-Z ]{0,30}PRIVATE KEY-----", 0, 1),
    Rule("bearer", r"eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+", 0, 24),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]+", 0, 40),
)
_MANY = 64


def _pieces(tree, fold: bool):
    """(exact strings or None, query) of a parse tree: the strings it can be, if few, and trigrams that it must hold."""
    exact: list[str] | None = [""]
    query: list[frozenset] = []
    skipped = False

    def close(strings):
        """What the strings read so far demand: every string's trigrams, as an OR of ANDs."""
        if strings and all(len(s.encode()) >= 3 for s in strings):
            query.append(frozenset(frozenset(s.encode()[i : i + 3] for i in range(len(s.encode()) - 2)) for s in strings))

    def follow(strings):
        nonlocal exact, skipped
        if strings is None or len(exact) * len(strings) > _MANY:
            close(exact)
            skipped = True
            exact = [""] if strings is None else list(strings)
        else:
            exact = [a + b for a in exact for b in strings]

    def go(items, fold):
        for op, arg in items:
            if op is sre.LITERAL:
                c = chr(arg)
                follow([c.lower() if c.isascii() else c])
            elif op is sre.SUBPATTERN:
                go(arg[3], fold or bool(arg[1] & re.IGNORECASE))
            elif op is sre.BRANCH:
                strings = []
                for branch in arg[1]:
                    part, extra = _pieces(branch, fold)
                    strings = None if strings is None or part is None or extra else strings + part
                follow(strings)
            elif op in (sre.MAX_REPEAT, sre.MIN_REPEAT) and arg[1] == 1 and arg[0] == 0:
                part, extra = _pieces(arg[2], fold)
                follow(None if part is None or extra else ["", *part])
            elif op is sre.IN and len(arg) <= 8 and all(k is sre.LITERAL for k, _ in arg):
                follow(sorted({chr(v).lower() for _, v in arg}))
            else:
                follow(None)

    go(tree, fold)
    if not skipped:
        return exact, []
    close(exact)
    return None, query


def trigram_query(pattern: str) -> list[frozenset]:
    """An AND of ORs of ANDs of lower-cased byte trigrams that every match of ``pattern`` holds; empty: all documents."""
    exact, query = _pieces(list(sre_parse.parse(pattern)), False)
    if exact is not None and exact and all(len(s.encode()) >= 3 for s in exact):
        query = [frozenset(frozenset(s.encode()[i : i + 3] for i in range(len(s.encode()) - 2)) for s in exact)]
    return query


class Scanner:
    """Rules with their queries; finds the spans of a slice of texts."""

    def __init__(self, rules: tuple[Rule, ...]):
        self.rules = [(r, re.compile(r.pattern, re.ASCII), trigram_query(r.pattern)) for r in rules]
        self.terms = sorted({t for _, _, q in self.rules for ors in q for ands in ors for t in ands})
        self.slot = np.full(1 << 24, -1, dtype=np.int16)
        for k, t in enumerate(self.terms):
            self.slot[t[0] | t[1] << 8 | t[2] << 16] = k
        self.lower = np.arange(256, dtype=np.uint8)
        self.lower[65:91] += 32

    def postings(self, texts: list[str]) -> list[set[int]]:
        """The documents of the segment that hold each term."""
        found: list[set[int]] = [set() for _ in self.terms]
        data = [t.encode("utf-8", "surrogatepass") for t in texts]
        ends = np.cumsum([len(d) + 2 for d in data])
        joined = self.lower[np.frombuffer(b"\0\0".join(data) + b"\0\0", dtype=np.uint8)]
        for at in range(0, max(0, len(joined) - 2), 1 << 20):
            b = joined[at : at + (1 << 20) + 2].astype(np.uint32)
            term = self.slot[b[:-2] | b[1:-1] << 8 | b[2:] << 16]
            where = np.flatnonzero(term >= 0)
            docs = np.searchsorted(ends, where + at, side="right")
            for t, d in set(zip(term[where].tolist(), docs.tolist(), strict=True)):
                found[t].add(d)
        return found

    def spans(self, texts: list[str]) -> list[list[tuple[int, int, int]]]:
        """(start, order of the rule, end) of each text's secrets, sorted."""
        posted = dict(zip(self.terms, self.postings(texts), strict=True))
        out: list[list[tuple[int, int, int]]] = [[] for _ in texts]
        for order, (rule, pattern, query) in enumerate(self.rules):
            kept: set[int] | None = None
            for ors in query:
                these = set().union(*(set.intersection(*(posted[t] for t in ands)) for ands in ors))
                kept = these if kept is None else kept & these
            for d in range(len(texts)) if kept is None else kept:
                for m in pattern.finditer(texts[d]):
                    if m.end(rule.group) - m.start(rule.group) >= rule.least:
                        out[d].append((m.start(), order, m.end()))
        for x in out:
            x.sort()
        return out


def find_secrets(docs: DataFrame, rules: tuple[Rule, ...] = BASE_RULES + MORE_RULES) -> DataFrame:
    """doc_id and the array of (kind, start, end) of each document."""

    def rows(scanner, ids, texts):
        found = scanner.spans([t or "" for t in texts])
        return {"doc_id": ids, "spans": [[{"kind": rules[k].kind, "start": s, "end": e} for s, k, e in x] for x in found]}

    return arrow_map(docs.select("doc_id", "text"), "doc_id long, spans array<struct<kind string, start int, end int>>", rows, start=lambda: Scanner(rules))


def secret_digests(docs: DataFrame, more: tuple[Rule, ...] = MORE_RULES) -> DataFrame:
    """doc_id, counts of the base kinds, digest of the base spans, and all spans as text."""
    rules = BASE_RULES + more

    def rows(scanner, ids, texts):
        found = scanner.spans([t or "" for t in texts])
        named = [[(rules[k].kind, f"{rules[k].kind}:{s}:{e}") for s, k, e in x] for x in found]
        base = {r.kind for r in BASE_RULES}
        out = {f"n_{r.kind}": [sum(k == r.kind for k, _ in x) for x in named] for r in BASE_RULES}
        return out | {"doc_id": ids, "base_sha256": [hashlib.sha256(",".join(s for k, s in x if k in base).encode()).hexdigest() for x in named], "spans": [",".join(s for _, s in x) for x in named]}

    return arrow_map(docs.select("doc_id", "text"), "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string", rows, start=lambda: Scanner(rules))


def redact_secrets(docs: DataFrame, mask: str = "[SECRET]", rules: tuple[Rule, ...] = BASE_RULES + MORE_RULES) -> DataFrame:
    """``docs`` with every span of every text replaced by ``mask`` (overlapping spans by one); n_chars follows. A null text stays null."""
    names = docs.columns
    ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)

    def rows(scanner, *columns):
        made = dict(zip(names, columns, strict=True))
        found = scanner.spans([t or "" for t in made["text"]])
        texts = []
        for text, spans in zip(made["text"], found, strict=True):
            parts, at = [], 0
            for s, _, e in spans:
                if s >= at:
                    parts += [text[at:s], mask]
                at = max(at, e)
            texts.append("".join([*parts, text[at:]]) if spans else text)
        made["text"] = texts
        if "n_chars" in made:
            made["n_chars"] = [n if not f else len(t) for n, f, t in zip(made["n_chars"], found, texts, strict=True)]
        return made

    return arrow_map(docs, ddl, rows, start=lambda: Scanner(rules))
