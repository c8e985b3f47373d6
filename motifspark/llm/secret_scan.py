"""Secret scan with a trigram inverted index.

Every rule is a regular expression over UTF-8 bytes.  From its syntax tree a Boolean
query is derived: a disjunction of sets of trigrams (lower case) that any match must
hold.  For each slice of texts a worker builds the inverted index of the trigrams that
the queries name (trigram -> texts, as bit rows), intersects and unites the postings,
and runs the expression on the candidates only.  A rule without mandatory trigrams
(a run of hexadecimal figures) scans every text.  The index of a slice is rebuilt by
whichever task has the slice, so nothing is shuffled and a lost executor costs its own
slices only.

Three base rules (assign, access, hex) are counted and hashed by themselves; further
rules only add spans.  Spans are of whole matches, in code points, end exclusive.

Defined results.  Null and empty texts have no spans.  Repeated rows are scanned one by
one.  An empty table gives no rows.  Extra columns are ignored.  Every rule looks at a byte
a bounded number of times, so that very long texts take time in proportion.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from re import _parser as syntax
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .arrow_text import map_arrow, slices, utf8


class Rule(NamedTuple):
    kind: str
    pattern: bytes
    flags: int = 0
    group: int = 0  # the group whose length counts
    least: int = 0  # its least length; shorter matches are dropped


#: Fixed values.  The first three are the base rules, in the order that breaks ties.
BASE = [
    Rule("assign", rb"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.IGNORECASE, 2, 8),
    Rule("access", rb"AKIA[A-Z0-9]+", 0, 0, 16),
    Rule("hex", rb"[0-9a-f]+", 0, 0, 32),
]
MORE = [
    Rule("private_key", rb"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----"),
    Rule("forge_token", rb"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat_token", rb"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("signed_token", rb"(?<![A-Za-z0-9_-])eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("bearer", rb"bearer\x20+[A-Za-z0-9._~+/-]{20,}", re.IGNORECASE),
    Rule("url_password", rb"[a-z][a-z0-9+.-]{0,30}://[^\s:/@]+:[^\s:/@]{4,}@"),
]
GAP = "\0"  # stands for any bytes in an expansion
MOST = 256  # expansions of one expression


def expansions(tree) -> list[str]:
    """Strings, with gaps, one of which every match holds."""
    out = [""]
    for op, arg in tree:
        parts = _node(op, arg)
        if len(out) * len(parts) > MOST:
            parts = [GAP]
        out = list(dict.fromkeys(a + b for a in out for b in parts))
    return out


def _node(op, arg) -> list[str]:
    name = str(op)
    if name == "LITERAL":
        return [chr(arg)]
    if name == "IN" and len(arg) <= 5 and all(str(o) == "LITERAL" for o, _ in arg):
        return [chr(c) for _, c in arg]
    if name == "BRANCH":
        out = [x for branch in arg[1] for x in expansions(branch)]
        return list(dict.fromkeys(out)) if len(out) <= MOST else [GAP]
    if name == "SUBPATTERN":
        return expansions(arg[-1])
    if name in ("MAX_REPEAT", "MIN_REPEAT", "POSSESSIVE_REPEAT"):
        low, high, inner = arg
        if low == 0:
            return [*expansions(inner), ""] if high == 1 else [GAP]
        one = expansions(inner)
        out = one
        for _ in range(min(low, 4) - 1):
            out = [a + b for a in out for b in one]
            if len(out) > MOST:
                return [GAP]
        return out if low == high and low <= 4 else [x + GAP for x in out]
    return [""] if name == "AT" else [GAP]


def trigram_query(rule: Rule) -> list[frozenset[bytes]] | None:
    """A disjunction of trigram sets; None where some way to match names no trigram."""
    out = set()
    for x in expansions(syntax.parse(rule.pattern, rule.flags)):
        x = x.lower()
        grams = frozenset(x[i : i + 3].encode("latin-1") for i in range(len(x) - 2) if GAP not in x[i : i + 3])
        if not grams:
            return None
        out.add(grams)
    return [s for s in out if not any(t < s for t in out)]


class Scanner:
    """Rules compiled once a worker: expressions, queries and the table of wanted trigrams."""

    def __init__(self, rules: list[Rule]):
        self.rules = [(r, re.compile(r.pattern, r.flags), trigram_query(r)) for r in rules]
        wanted = sorted({g for _, _, q in self.rules for s in q or () for g in s})
        self.row = {g: i for i, g in enumerate(wanted)}
        self.lower = np.arange(256, dtype=np.uint8)
        self.lower[65:91] += 32
        self.slot = np.full(1 << 24, -1, dtype=np.int16)
        for g, i in self.row.items():
            self.slot[int.from_bytes(g, "big")] = i

    def postings(self, buf: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Bit rows: trigram by text."""
        out = np.zeros((len(self.row), len(off) - 1), dtype=bool)
        if len(buf) >= 3 and self.row:
            low = self.lower[buf].astype(np.int32)
            found = self.slot[(low[:-2] << 16) | (low[1:-1] << 8) | low[2:]]
            at = np.flatnonzero(found >= 0)
            text = np.searchsorted(off, at, "right") - 1
            inside = at + 3 <= off[text + 1]
            out[found[at[inside]], text[inside]] = True
        return out

    def candidates(self, query, postings: np.ndarray) -> np.ndarray:
        if query is None:
            return np.arange(postings.shape[1])
        hit = np.zeros(postings.shape[1], dtype=bool)
        for grams in query:
            hit |= np.logical_and.reduce(postings[[self.row[g] for g in grams]], axis=0)
        return np.flatnonzero(hit)

    def scan(self, buf: np.ndarray, off: np.ndarray) -> list[list[tuple[int, int, int]]]:
        """For each text its spans in bytes: (start, rule number, end), sorted."""
        postings, data = self.postings(buf, off), buf.tobytes()
        out: list[list[tuple[int, int, int]]] = [[] for _ in range(len(off) - 1)]
        for k, (rule, expression, query) in enumerate(self.rules):
            for t in self.candidates(query, postings).tolist():
                a, b = int(off[t]), int(off[t + 1])
                for m in expression.finditer(data[a:b]):
                    if m.end(rule.group) - m.start(rule.group) >= rule.least:
                        out[t].append((m.start(), k, m.end()))
        for spans in out:
            spans.sort()
        return out


def rendered(spans: list[tuple[int, int, int]], text: bytes, kinds: list[str]) -> list[tuple[str, str]]:
    """(kind, kind:start:end) in code points."""
    if not spans:
        return []
    heads = np.concatenate(([0], np.cumsum((np.frombuffer(text, dtype=np.uint8) & 0xC0) != 0x80)))
    return [(kinds[k], f"{kinds[k]}:{heads[a]}:{heads[b]}") for a, k, b in spans]


SCHEMA = "doc_id bigint, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string, n_spans bigint"


def scan(docs: DataFrame, rules: list[Rule] | None = None) -> DataFrame:
    """One row a document: counts of base spans, their digest, and all spans."""
    rules = list(BASE + MORE if rules is None else rules)
    base = [r.kind for r in BASE]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner, kinds = Scanner(rules), [r.kind for r in rules]
        for batch in batches:
            for part in slices(batch, "text"):
                buf, off = utf8(part.column(1))
                rows = []
                for t, spans in enumerate(scanner.scan(buf, off)):
                    said = rendered(spans, buf[off[t] : off[t + 1]].tobytes(), kinds) if spans else []
                    plain = ",".join(s for k, s in said if k in base)
                    rows.append((*(sum(k == b for k, _ in said) for b in base), hashlib.sha256(plain.encode()).hexdigest(), ",".join(s for _, s in said), len(said)))
                cols = list(zip(*rows, strict=True))
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, pa.int64()) for c in cols[:3]), *(pa.array(c, pa.string()) for c in cols[3:5]), pa.array(cols[5], pa.int64())], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_spans"])

    return map_arrow(docs.select("doc_id", "text"), work, SCHEMA)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
