"""Secret scans by assignment-aware lexing.

A small lexer reads source and configuration syntax (``name = "literal"``, ``name: literal``, ``"name": "literal"``,
``export NAME=literal``, ``name := literal``, ``name => literal``, command-line ``--name literal``) into name-literal
pairs, joins literals with ``+``, follows names that were bound earlier in the same text (constants propagate), and
scores each literal by how sensitive its target's name is and how much the literal looks like a key.  Spans of literals
at or over ``threshold`` are added as kind ``literal``; the base patterns' spans stay.

Defined results: null or empty text has no span; repeated rows are scanned one by one; an empty table gives an empty
result; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .common import batch_texts, only, rows_with

KINDS = ("assign", "access", "hex")
SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_literal long"
Span = tuple[str, int, int]

# The base patterns.  ASCII letters alone fold case.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")

#: Parts of a target's name that make it sensitive, with weights.
SENSITIVE = {
    "password": 3, "passwd": 3, "passphrase": 3, "pwd": 3, "pass": 2, "secret": 3, "token": 3, "apikey": 3, "key": 2, "credential": 3, "credentials": 3,
    "auth": 2, "private": 2, "access": 1, "api": 1, "client": 1, "bearer": 2, "signature": 1, "cert": 1, "salt": 2, "session": 1, "db": 1, "dsn": 2,
}
PLACEHOLDERS = re.compile(r"(?i)^(x{3,}|\*+|\.+|changeme|change_me|example|none|null|nil|true|false|todo|your[_-].*|<.*>|\$\{.*\}|\{\{.*\}\}|placeholder|undefined)$")
NAME = r"""["']?(?P<name>[A-Za-z_][A-Za-z0-9_.-]*)["']?"""
PAIR = re.compile(NAME + r"[\x20\t]*(?::=|=>|[:=](?![=/:]))[\x20\t]*")
FLAG = re.compile(r"(?<![^\x20\t\n])--(?P<name>[A-Za-z][A-Za-z0-9_-]*)[\x20\t]+(?=[^\x20\t\n-])")
QUOTED = re.compile(r'"((?:[^"\\\n]++|\\.)*+)"' + r"|'((?:[^'\\\n]++|\\.)*+)'")
BARE = re.compile(r"[^\x20\t\r\n\"',;(){}\[\]<>]+")
PLUS = re.compile(r"[\x20\t]*\+[\x20\t]*")
#: What a pair is found by: the lexer looks back from here, at most to the pair before.
OPERATOR = re.compile(r"[:=]|--")


def base_spans(text: str) -> list[Span]:
    """All spans of the base patterns by start, then kind; offsets are code points."""
    found = [("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6] if "=" in text or ":" in text else []
    found += [("access", *m.span()) for m in ACCESS.finditer(text) if len(m[0]) >= 20] if "AKIA" in text else []
    found += [("hex", *m.span()) for m in HEX.finditer(text)]
    return sorted(found, key=lambda s: (s[1], KINDS.index(s[0])))


def name_score(name: str) -> int:
    """Sum of the weights of a name's parts: split at punctuation and where case changes."""
    parts = re.findall(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|[0-9]+", name)
    words = [p.lower() for p in parts]
    joined = {"".join(words[i : i + 2]) for i in range(len(words) - 1)}
    return sum(SENSITIVE.get(w, 0) for w in {*words, *joined})


def literal_score(value: str) -> float:
    """0 for placeholders and plain words; grows with length, character classes and entropy."""
    if len(value) < 6 or PLACEHOLDERS.match(value):
        return 0.0
    classes = sum(bool(re.search(c, value)) for c in ("[a-z]", "[A-Z]", "[0-9]", "[^A-Za-z0-9]"))
    counts = Counter(value).values()
    total = sum(counts)
    entropy = -sum(c / total * math.log2(c / total) for c in counts)
    if classes < 2 or not re.search("[0-9]", value) and entropy < 3.5:
        return 0.0
    return min(3.0, entropy / 1.5) + (len(value) >= 16)


def pairs(text: str) -> list[tuple[str, list[tuple[int, int]], str]]:
    """(name, literal spans, value) of each assignment in order of the text, with constants propagated."""
    bound: dict[str, tuple[list[tuple[int, int]], str]] = {}
    out = []
    done = 0
    for op in OPERATOR.finditer(text):
        if op.start() < done:
            continue
        m = None
        if op[0] == "--":
            m = FLAG.match(text, op.start())
        else:
            at = op.start()
            while at > done and text[at - 1] in " \t":
                at -= 1
            lo = at - 1 if at > done and text[at - 1] in "\"'" else at
            start = lo
            while start > done and (text[start - 1].isascii() and (text[start - 1].isalnum() or text[start - 1] in "_.-")):
                start -= 1
            while start < lo and not (text[start].isalpha() or text[start] == "_"):
                start += 1
            m = PAIR.match(text, start) if start < lo else None
        if not m or m.end() <= op.start():
            continue
        at, spans, value = m.end(), [], []
        while True:
            if q := QUOTED.match(text, at):
                group = 1 if q[1] is not None else 2
                spans.append(q.span(group))
                value.append(q[group])
            elif b := BARE.match(text, at):
                q, known = b, bound.get(b[0])
                spans += known[0] if known else [b.span()]
                value.append(known[1] if known else b[0])
            else:
                break
            at = q.end()
            plus = PLUS.match(text, at)
            if not plus:
                break
            at = plus.end()
        if spans:
            name, whole = m["name"], "".join(value)
            bound[name] = (spans, whole)
            out.append((name, spans, whole))
        done = max(done, at)
    return out


def added_spans(text: str, base: list[Span], threshold: float = 4.0) -> list[Span]:
    """Literal spans of sensitive assignments that touch no base span."""
    found: set[tuple[int, int]] = set()
    for name, spans, value in pairs(text):
        sensitive = name_score(name)
        if sensitive >= 2 and sensitive + literal_score(value) >= threshold and literal_score(value) > 0:
            found.update(s for s in spans if s[1] - s[0] >= 3)
    taken = sorted((a, b) for _, a, b in base)
    return [("literal", a, b) for a, b in sorted(found) if not any(x < b and a < y for x, y in taken)]


def joined(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def _bytes(chars: bytes) -> np.ndarray:
    return np.isin(np.arange(256), np.frombuffer(chars, np.uint8))


def find_all(column: pa.Array) -> list[tuple[list[Span], list[Span]]]:
    """(base, all) spans of each text; only texts that hold an operator, a long hexadecimal run or AKIA are decoded."""
    raw, starts, ends = batch_texts(column)
    out: list[tuple[list[Span], list[Span]]] = [([], [])] * len(column)
    if not len(raw):
        return out
    busy = rows_with(raw, starts, ends, _bytes(b"=:")) | _has(raw, starts, ends, b"--") | _has(raw, starts, ends, b"AKIA")
    in_hex = np.concatenate([[0], np.cumsum(~_bytes(b"0123456789abcdef")[raw], dtype=np.int64)])
    run = np.flatnonzero(in_hex[24:] == in_hex[:-24]) if len(raw) >= 24 else np.empty(0, np.int64)
    if len(run):
        busy |= np.searchsorted(run, ends) > np.searchsorted(run, starts)
    for i in np.flatnonzero(busy):
        text = raw[starts[i] : ends[i]].tobytes().decode("utf-8", "surrogatepass")
        base = base_spans(text)
        more = added_spans(text, base)
        order = {k: n for n, k in enumerate((*KINDS, "literal"))}
        out[i] = (base, sorted([*base, *more], key=lambda s: (s[1], order[s[0]])))
    return out


def _has(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, needle: bytes) -> np.ndarray:
    blob, at, hits = raw.tobytes(), -1, []
    while (at := blob.find(needle, at + 1)) >= 0:
        hits.append(at)
    hits = np.array(hits, np.int64)
    return np.searchsorted(hits, ends) > np.searchsorted(hits, starts)


def secret_spans(docs: DataFrame) -> DataFrame:
    """Counts of base spans, their digest and all spans, per row of ``docs`` (doc_id, text).  Narrow: no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = find_all(batch.column(1))
            counts = [pa.array([sum(s[0] == k for s in b) for b, _ in found], pa.int64()) for k in KINDS]
            digest = pa.array([hashlib.sha256(joined(b).encode()).hexdigest() for b, _ in found], pa.string())
            spans, more = pa.array([joined(a) for _, a in found], pa.string()), pa.array([len(a) - len(b) for b, a in found], pa.int64())
            yield pa.RecordBatch.from_arrays([pc.cast(batch.column(0), pa.int64()), *counts, digest, spans, more], names=[c.strip().split()[0] for c in SCHEMA.split(",")])

    return only(docs, "doc_id", "text").mapInArrow(run, SCHEMA)
