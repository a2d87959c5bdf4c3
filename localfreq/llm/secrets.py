"""Secret scans by assignment-aware lexing.

Two finders work on the whole of each text. The *base* finder reports fixed shapes: sensitive
assignments, access-key identifiers and long lower-case hexadecimal runs. The *lexer* finds name-literal
pairs of source and configuration syntax (``name = "x"``, ``"name": "x"``, ``name => x``, ``name := x``),
follows names that stand for a constant seen before, and scores each literal by its shape and by how
sensitive its target's name is. Literals at or over the threshold become spans of kind ``literal``. Literals joined by
an operator, by standing side by side, or within parentheses are scored as one value and give a span each. What a
comment assigns is scored too, but defines no constant.

Nulls and empty texts have no spans. A text's spans depend on that text alone, so repeated rows get equal
results; rows are never dropped and nothing is shuffled.
"""

from __future__ import annotations

import hashlib
import math
import re
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from localfreq.llm.common import batches, read_table, texts_of

__all__ = ["KINDS", "find_spans", "literal_score", "name_weight", "op10_secret_scans", "redact", "scan_secrets"]

#: Kinds in their listed order, the added kind last.
KINDS = ("assign", "access", "hex", "literal")

#: The shapes of the base finder.
_ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.IGNORECASE | re.ASCII)
_ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
_HEX = re.compile(r"[0-9a-f]{16,}")
_ASSIGN_LEAST = 12

#: Parts of names and how sensitive they are.
_PARTS = {
    "password": 1.0, "passwd": 1.0, "passphrase": 1.0, "pwd": 0.9, "secret": 1.0, "token": 0.9, "apikey": 1.0, "credential": 0.9,
    "credentials": 0.9, "private": 0.6, "bearer": 0.8, "auth": 0.6, "key": 0.5, "access": 0.3, "api": 0.3, "signing": 0.4, "client": 0.1, "salt": 0.4, "pass": 0.8,
}
_NOT_SECRET = re.compile(r"^(?:true|false|null|none|nil|undefined|yes|no|example\w*|change_?me|placeholder|your\w*|x{3,}|\*{3,}|<.*>|\$\{.*\}|\{\{.*\}\})$", re.IGNORECASE)
_WORDS = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+")
#: A name read backwards from its operator. Neither this nor a quoted value runs past the next operator or quote of its kind, so unbounded lengths cost one scan;
#: a value without quotes has at most eight operators inside, each of which begins a pair of its own.
_NAME = re.compile(r"\n?[ \t]*+\]?[\"']?([A-Za-z0-9_.-]*[A-Za-z_])")
_QUOTED = r"\"(?:[^\"\\\n]++|\\.)++\"|'(?:[^'\\\n]++|\\.)++'"
_VALUE = re.compile(rf"[>=]?[ \t]*+(?:/\*[^*\n]*+\*/[ \t]*+)?(?:(?P<open>\()[ \t\n]*+(?=[\"']))?(?:(?P<quoted>{_QUOTED})|(?=[^\s,;\"'#(){{}}\[\]])(?P<bare>(?:[^\s,;\"'#(){{}}\[\]=:]*+[=:]){{0,8}}[^\s,;\"'#(){{}}\[\]=:]*+))")
#: The next literal of a concatenation: after an operator, or beside its neighbour on one (continued) line; in parentheses lines may change freely. No name of a pair.
_JOINED = re.compile(rf"(?:[ \t]*+(?:\\?\n[ \t]*+)?(?:\+|\.\.?|&)[ \t]*+(?:\\?\n[ \t]*+)?|[ \t]*+(?:\\\n[ \t]*+)?)({_QUOTED})(?![ \t]*+[:=])")
_JOINED_OPEN = re.compile(rf"[ \t\n]*+(?:(?:\+|\.\.?|&)[ \t\n]*+)?({_QUOTED})(?![ \t]*+[:=])")
#: Lines that are comments, and where a block comment begins.
_COMMENT = re.compile(r"^[ \t]*+(?:#|//|--|;)[^\n]*+|/\*", re.MULTILINE)
_OPERATOR = re.compile(r"[:=]")
_BASE_HINTS = ("passw", "secret", "token", "api")


def name_weight(name: str) -> float:
    """How sensitive a target's name is, 0 to 1: the sum of its parts, cut at 1."""
    parts = [w.lower() for w in _WORDS.findall(name)]
    joined = {a + b for a, b in zip(parts, parts[1:], strict=False)}
    return min(1.0, sum(_PARTS.get(w, 0.0) for w in {*parts, *joined}))


def literal_score(name: str, value: str) -> float:
    """Sensitivity of the name times the literal's likeness to a generated value, 0 to 1."""
    weight = name_weight(name)
    if not weight or len(value) < 8 or _NOT_SECRET.match(value) or " " in value:
        return 0.0
    n = len(value)
    entropy = -sum(c / n * math.log2(c / n) for c in Counter(value).values())
    classes = sum(bool(re.search(p, value)) for p in ("[a-z]", "[A-Z]", "[0-9]", "[^A-Za-z0-9]"))
    shape = 0.5 * min(1.0, entropy / 3.5) + 0.2 * min(1.0, n / 20) + 0.3 * min(1.0, (classes - 1) / 2)
    return weight * shape


def _comments(text: str) -> Iterator[tuple[int, int]]:
    """Start and end of each comment line and closed block comment, in text order."""
    at, last = 0, text.rfind("*/")
    while m := _COMMENT.search(text, at):
        at = m.end()
        if m.group() != "/*":
            yield m.span()
        elif m.end() <= last:
            at = text.index("*/", m.end()) + 2
            yield m.start(), at


def _pairs(text: str) -> Iterator[tuple[str, str, list[tuple[int, int]], bool, int]]:
    """(name, value, spans of its literals, quoted, place of the operator) of each assignment-like pair, in text order."""
    back = text[::-1]
    for m in _OPERATOR.finditer(text):
        p = m.start()
        before, after = text[p - 1:p], text[p + 1:p + 2]
        if before in ("=", "!", "<", ">", ":") or after == "/" or (after == "=" and m.group() == "="):
            continue
        name = _NAME.match(back, len(text) - p)
        value = name and _VALUE.match(text, p + 1)
        if not value:
            continue
        if value["quoted"] is None:
            yield name.group(1)[::-1], value["bare"], [value.span("bare")], False, p
            continue
        spans, more = [value.span("quoted")], _JOINED_OPEN if value["open"] else _JOINED
        while piece := more.match(text, spans[-1][1]):
            spans.append(piece.span(1))
        spans = [(s + 1, e - 1) for s, e in spans]
        yield name.group(1)[::-1], "".join(text[s:e] for s, e in spans), spans, True, p


def _union(spans: list[tuple[int, int, int]]) -> tuple[list[int], list[int]]:
    """Starts and ends of the stretches that sorted spans cover."""
    starts: list[int] = []
    ends: list[int] = []
    for s, _, e in spans:
        if ends and s <= ends[-1]:
            ends[-1] = max(ends[-1], e)
        else:
            starts.append(s)
            ends.append(e)
    return starts, ends


def _covered(span: tuple[int, int], starts: list[int], ends: list[int]) -> bool:
    """Whether one of the stretches holds all of the span."""
    i = bisect_right(starts, span[0]) - 1
    return i >= 0 and span[1] <= ends[i]


def find_spans(text: str | None, threshold: float = 0.45) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """(base, added) spans as (start, kind's place in KINDS, end), each sorted; places count code points."""
    if not text:
        return [], []
    base: list[tuple[int, int, int]] = []
    low = text.lower()
    if any(h in low for h in _BASE_HINTS):
        base += [(m.start(), 0, m.end()) for m in _ASSIGN.finditer(text) if m.end(2) - m.start(2) >= _ASSIGN_LEAST]
    if "AKIA" in text:
        base += [(m.start(), 1, m.end()) for m in _ACCESS.finditer(text)]
    base += [(m.start(), 2, m.end()) for m in _HEX.finditer(text)]
    base.sort()
    added: list[tuple[int, int, int]] = []
    if "=" in text or ":" in text:
        starts, ends = _union(base)
        known: dict[str, tuple[str, list[tuple[int, int]]]] = {}
        seen = set()
        comments = _comments(text)
        inside = next(comments, None)
        for name, value, spans, quoted, p in _pairs(text):
            while inside and inside[1] <= p:
                inside = next(comments, None)
            literal = (value, spans) if quoted else known.get(value, (value, spans))
            if not inside or p < inside[0]:  # what a comment assigns is judged, but no constant
                known[name] = literal
            value, spans = literal
            left = [x for x in spans if x not in seen and not _covered(x, starts, ends)]
            if left and literal_score(name, value) >= threshold:
                seen.update(left)
                added += [(s, 3, e) for s, e in left]
        added.sort()
    return base, added


def _joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def scan_secrets(df: DataFrame, *, doc_id: str = "doc_id", text: str = "text", threshold: float = 0.45) -> DataFrame:
    """One row per row of ``df``: the id, base counts, base digest and all spans. Narrow: no shuffle."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(rows):
            counts, digest, spans = [], [], []
            for t in texts_of(b.column(1)):
                base, added = find_spans(t, threshold)
                c = Counter(k for _, k, _ in base)
                counts.append((c[0], c[1], c[2]))
                digest.append(hashlib.sha256(_joined(base).encode()).hexdigest())
                spans.append(_joined(sorted(base + added)))
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([c[i] for c in counts], pa.int64()) for i in range(3)), pa.array(digest, pa.string()), pa.array(spans, pa.string())], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return df.select(df[doc_id].cast("long").alias("doc_id"), df[text].cast("string").alias("text")).mapInArrow(run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def redact(df: DataFrame, *, text: str = "text", mark: str = "[SECRET]", threshold: float = 0.45) -> DataFrame:
    """``df`` with every span of its texts replaced by ``mark``; null texts stay null, other columns stay as they are.

    Overlapping spans become one mark. ``n_chars``, where there is one, follows the new text.
    """
    names = df.columns
    at, size = names.index(text), names.index("n_chars") if "n_chars" in names else None

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches(rows):
            out = []
            for t in b.column(at).to_pylist():
                base, added = find_spans(t, threshold)
                done, parts = 0, []
                for s, _, e in sorted(base + added):
                    if s >= done:
                        parts += [t[done:s], mark]
                    done = max(done, e)
                out.append("".join([*parts, t[done:]]) if parts else t)
            cols = list(b.columns)
            cols[at] = pa.array(out, b.schema.field(at).type)
            if size is not None:
                old = cols[size].to_pylist()
                cols[size] = pa.array([o if t is None else len(t) for t, o in zip(out, old, strict=True)], b.schema.field(size).type)
            yield pa.RecordBatch.from_arrays(cols, schema=b.schema)

    return df.mapInArrow(run, df.schema)


def op10_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_secrets(read_table(spark, sf_dir, "documents"))
