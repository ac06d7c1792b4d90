"""Secret scans over a trigram inverted index.

Each rule is a regular expression. From its parse tree we derive a Boolean query over trigrams that every match
must satisfy. A segment (a run of rows of one Arrow batch) is indexed on just the trigrams that some query names:
postings are bit sets of rows. Queries intersect and unite postings; the candidates are verified by the rule
itself on the whole text. A rule whose query is trivially true scans every text. Postings never leave their
segment, so nothing is shuffled and memory is bounded by a segment.

Null texts are empty texts. Positions are code points, ends exclusive. Texts of any length are scanned whole. Spans that begin at one place are
ordered by the rule, in the order the rules are listed. Repeated rows, and rows with an equal or null doc_id, keep their rows and get equal
results. An empty table gives an empty result. Only doc_id and text are read, so other columns may have any names.
"""
from __future__ import annotations

import hashlib
import re
from re import _constants as C
from re import _parser as parser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import text_batches

# The three base kinds in their listed order, then the kinds this operator adds.
# name, pattern, group whose length is tested, least length
BASE_RULES = [
    ("assign", r"""(?ai:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 1, 8),
    ("access", r"AKIA[A-Z0-9]+", 0, 16),
    ("hex", r"[0-9a-f]+", 0, 32),
]
ADDED_RULES = [
    ("github", r"gh[pousr]_[A-Za-z0-9]{36,}", 0, 40),
    ("slack", r"xox[abprs]-[A-Za-z0-9-]{10,}", 0, 15),
    ("google", r"AIza[0-9A-Za-z_-]{35}", 0, 39),
    ("stripe", r"[sr]k_(?:live|test)_[0-9A-Za-z]{16,}", 0, 24),
    ("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 30),
    ("pem", r"-----BEGIN [A-Z ]{0,24}PRIVATE KEY-----", 0, 27),
]
SEGMENT_CHARS = 4 << 20
MOST_STRINGS = 16  # exact sets beyond this are no longer multiplied out

ANY = ("any",)


def _and(*qs):
    parts = {q for q in qs if q != ANY}
    return ANY if not parts else next(iter(parts)) if len(parts) == 1 else ("and", frozenset(parts))


def _or(*qs):
    if ANY in qs:
        return ANY
    parts = set(qs)
    return next(iter(parts)) if len(parts) == 1 else ("or", frozenset(parts))


def _of_strings(strings):
    """Every match holds one of `strings`: the trigrams of one of them are all there."""
    if any(len(s) < 3 for s in strings):
        return ANY
    return _or(*(_and(*(("tri", s[i : i + 3]) for i in range(len(s) - 2))) for s in strings))


def _cover(op, arg):
    """The strings a single-character node can be, in lower case, or None if too many."""
    if op is C.LITERAL:
        return {chr(arg).lower()} if arg < 128 else None
    if op is C.IN:
        out = set()
        for kind, v in arg:
            if kind is C.LITERAL and v < 128:
                out.add(chr(v).lower())
            elif kind is C.RANGE and v[1] < 128 and v[1] - v[0] < MOST_STRINGS:
                out |= {chr(c).lower() for c in range(v[0], v[1] + 1)}
            else:
                return None
        return out if len(out) <= MOST_STRINGS else None
    return None


def _items(tree):
    """(exact strings or None, query) for a sequence of nodes: exact runs grow by product and are flushed as trigrams."""
    run, query, exact = {""}, ANY, True
    for op, arg in tree:
        got, sub = _node(op, arg)
        if got is not None and len(got) * len(run) <= MOST_STRINGS * 4:
            run = {a + b for a in run for b in got}
            continue
        query, exact = _and(query, _of_strings(run), sub), False
        run = got if got is not None else {""}
    return (run, ANY) if exact else (None, _and(query, _of_strings(run)))


def _node(op, arg):
    one = _cover(op, arg)
    if one is not None:
        return one, ANY
    if op is C.SUBPATTERN:
        return _items(arg[-1])
    if op is C.BRANCH:
        subs = [_items(x) for x in arg[1]]
        if all(e is not None for e, _ in subs) and sum(len(e) for e, _ in subs) <= MOST_STRINGS:
            return set().union(*(e for e, _ in subs)), ANY
        return None, _or(*(_of_strings(e) if e is not None else q for e, q in subs))
    if op in (C.MAX_REPEAT, C.MIN_REPEAT, C.POSSESSIVE_REPEAT):
        low, high, sub = arg
        e, q = _items(sub)
        if high == 1 and low == 0 and e is not None:
            return e | {""}, ANY
        if low == 0:
            return None, ANY
        if low == high == 1:
            return e, q
        return None, _of_strings(e) if e is not None else q
    if op in (C.AT, C.ASSERT, C.ASSERT_NOT):
        return {""}, ANY
    return None, ANY


def trigram_query(pattern: str):
    """A Boolean query over lower-case ASCII trigrams that each match's text meets; ("any",) if there is none."""
    exact, query = _items(parser.parse(pattern))
    return _of_strings(exact) if exact is not None else query


def trigrams_of(query) -> set[str]:
    if query[0] == "tri":
        return {query[1]}
    return set() if query == ANY else set().union(*map(trigrams_of, query[1]))


class Segment:
    """Postings of the wanted trigrams over some texts, as bit sets of rows in Python integers."""

    def __init__(self, texts: list[str], wanted: np.ndarray, names: list[str]):
        raw = [t.encode("utf-8", "surrogatepass") for t in texts]
        self.all = (1 << len(texts)) - 1
        self.postings = dict.fromkeys(names, 0)
        ends = np.cumsum([len(r) + 3 for r in raw])
        flat = np.frombuffer(b"\0\0\0".join(raw) + b"\0\0\0", np.uint8)
        low = LOWER[flat].astype(np.uint32)
        which = wanted[(low[:-2] << 16) | (low[1:-1] << 8) | low[2:]]
        at = np.flatnonzero(which)
        pairs = np.unique(np.searchsorted(ends, at, "right").astype(np.int64) << 16 | which[at])
        for p in pairs.tolist():
            self.postings[names[(p & 0xFFFF) - 1]] |= 1 << (p >> 16)

    def rows(self, query) -> int:
        if query == ANY:
            return self.all
        if query[0] == "tri":
            return self.postings[query[1]]
        out = self.all if query[0] == "and" else 0
        for q in query[1]:
            out = out & self.rows(q) if query[0] == "and" else out | self.rows(q)
        return out


LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


class Scanner:
    def __init__(self, rules):
        self.rules = [(name, re.compile(p), g, n, trigram_query(p)) for name, p, g, n in rules]
        self.names = sorted(set().union(*(trigrams_of(r[4]) for r in self.rules)))
        self.wanted = np.zeros(1 << 24, np.uint16)
        for k, t in enumerate(self.names):
            a, b, c = t.encode()
            self.wanted[a << 16 | b << 8 | c] = k + 1

    def scan(self, texts: list[str]) -> list[list[tuple[int, int, int]]]:
        """(start, kind, end) of each text's spans, sorted."""
        found: list[list] = [[] for _ in texts]
        segment = Segment(texts, self.wanted, self.names)
        for kind, (name, rx, group, least, query) in enumerate(self.rules):
            # a run of 32 hex digits begins where a run begins, so shorter ones need not be listed to be dropped
            rx = HEX_RUN if name == "hex" else rx
            rows = segment.rows(query)
            for k in range(len(texts)) if rows == segment.all else _bits(rows):
                for m in rx.finditer(texts[k]):
                    if m.end(group) - m.start(group) >= least:
                        found[k].append((m.start(), kind, m.end()))
        for f in found:
            f.sort()
        return found


HEX_RUN = re.compile(r"[0-9a-f]{32,}")


def _bits(n: int):
    while n:
        low = n & -n
        yield low.bit_length() - 1
        n ^= low


_scanners: dict = {}


def _scan(rules, n_base: int):
    def run(batches):
        if rules not in _scanners:
            _scanners[rules] = Scanner(rules)
        scanner = _scanners[rules]
        for batch in batches:
            ids, col, at = batch.column(0), batch.column(1), 0
            while at < batch.num_rows:
                texts, chars = [], 0
                while at + len(texts) < batch.num_rows and chars < SEGMENT_CHARS:
                    texts.append(col[at + len(texts)].as_py())
                    chars += len(texts[-1])
                spans = scanner.scan(texts)
                as_text = [[(k, f"{rules[k][0]}:{a}:{b}") for a, k, b in s] for s in spans]
                counts = [[sum(k == kind for _, k, _ in s) for s in spans] for kind in range(n_base)]
                digests = [hashlib.sha256(",".join(x for k, x in s if k < n_base).encode()).hexdigest() for s in as_text]
                yield pa.RecordBatch.from_arrays([ids.slice(at, len(texts)), *[pa.array(c, pa.int64()) for c in counts], pa.array(digests), pa.array([",".join(x for _, x in s) for s in as_text])], names=["doc_id", *[f"n_{rules[k][0]}" for k in range(n_base)], "base_sha256", "spans"])
                at += len(texts)

    return run


def find_secrets(docs: DataFrame, added: list[tuple] = ADDED_RULES) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans; one row per row of `docs` (doc_id, text)."""
    rules = tuple(BASE_RULES) + tuple(added)
    return text_batches(docs, _scan(rules, len(BASE_RULES)), "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
