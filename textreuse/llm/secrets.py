"""Secret scans: fixed base patterns and an assignment-aware lexer.

Base: three patterns over the whole text, leftmost and non-overlapping for each kind.
Method: source and configuration syntax is read as name-literal pairs (``name = "x"``,
``"name": "x"``, ``name := x``, ``name => x``, typed declarations, attributes). The
right side may join literals and names; a name stands for its last assignment before
that place, or else its first after it. Constants are propagated through names to any
depth, and each literal is scored by the most sensitive name that it reaches: words of
the name, length, entropy and mix of what the name stands for, with placeholders left
out. What a name stands for is never spelt out: it is summed up (:class:`Value`), so
that a chain of any length, or one that doubles, takes linear time. Names that need
themselves stand for what is known outside the loop. Literals that score enough become spans of kind ``literal``, unless base
matches contain them whole: a base value ends at the first symbol outside its set, and
the literal around it goes on. Redaction replaces the union of values and literals.

Cases: a null or empty text has no spans. Repeated rows give equal rows. Very long
texts are read whole in linear time: names start only at a token's start, and neighbours
in a pattern share no character, so that nothing is read again and again. Spans that tie
at a start stand in the order of ``KINDS``. Other columns are passed by, whatever their
names. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator
from math import log2

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KINDS = ("assign", "access", "hex", "literal")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
#: Marks bytes of hex digits, so that a run of 24 is found by one search.
_HEX_RUN = bytes(120 if chr(b) in "0123456789abcdef" else 32 for b in range(256))

_PAIR = re.compile(r"""(?<![A-Za-z0-9_.$-])(["']?)([A-Za-z_$][A-Za-z0-9_.$-]*+)\1[ \t]*+(?::[ \t]*+[A-Za-z_][\w\[\],.]*+(?:[ \t]++[\w\[\],.]++)*+[ \t]*+=(?![=>])|:=|=>|=(?![=>])|:(?!//|:))[ \t]*+""")
_QUOTED = re.compile(r'''"""(.*?)"""|\'\'\'(.*?)\'\'\'|"((?:[^"\\\n]|\\.)*)"|'((?:[^'\\\n]|\\.)*)'|`([^`]*)`''', re.DOTALL)
_NAME = re.compile(r"\$?\{?([A-Za-z_][A-Za-z0-9_.]*)\}?")
_BARE = re.compile(r"""[^\s"'`,;(){}\[\]<>]+""")
_JOIN = re.compile(r"[ \t]*+(?:\+|\.\.?|&|\\?\n[ \t]*+\+)[ \t]*+(?=[\"'`$A-Za-z_])")
_PART = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|[0-9]+")
_WORDS = r"example|sample|changeme|change_me|placeholder|your|dummy|redacted|xxxx|\*\*\*|<|\$\{|%\("
_PLACEHOLDER_WORD = re.compile(_WORDS, re.IGNORECASE)
_PLACEHOLDER = re.compile(_WORDS + r"|^(?:true|false|null|none|nil|undefined)$|^(.)\1*$", re.IGNORECASE)

STRONG = frozenset({"password", "passwd", "pwd", "passphrase", "secret", "token", "apikey", "credential", "credentials", "bearer", "privatekey"})
WEAK = frozenset({"key", "auth", "salt", "signature", "private", "session", "jwt", "dsn", "pass", "cert", "pin"})
PAIRED = frozenset({("api", "key"), ("access", "key"), ("private", "key"), ("secret", "key"), ("signing", "key"), ("encryption", "key"), ("account", "key"), ("auth", "key"), ("client", "key")})
LEAST_SCORE = 0.5


def base_spans(text: str) -> list[tuple[int, int, str, int]]:
    """``(start, end, kind, start of the value)`` of the base matches."""
    found = []
    if ":" in text or "=" in text:
        found += [(m.start(), m.end(), "assign", m.start(2)) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        found += [(m.start(), m.end(), "access", m.start()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    if b"x" * 24 in text.encode("utf-8", "surrogatepass").translate(_HEX_RUN):
        found += [(m.start(), m.end(), "hex", m.start()) for m in HEX.finditer(text) if m.end() - m.start() >= 24]
    return found


def name_weight(name: str) -> float:
    """How sensitive the words of a name are, 0 to 1."""
    parts = [p.lower() for p in _PART.findall(name)]
    if STRONG & {*parts, "".join(parts[-2:])} or PAIRED & {*zip(parts, parts[1:], strict=False)}:
        return 1.0
    return 0.6 if WEAK & set(parts) else 0.0


#: No shorter than any word of the placeholder pattern, so that one that spans two parts stands whole in their ends.
_REACH = 16


class Value:
    """What is known of a text made of parts: length, counts of its characters, both ends, and whether it has a placeholder."""

    __slots__ = ("counts", "first", "last", "length", "placeholder")

    def __init__(self, text: str = ""):
        self.length, self.counts = len(text), Counter(text)
        self.first, self.last = text[:_REACH], text[-_REACH:]
        self.placeholder = bool(_PLACEHOLDER.search(text))

    def __add__(self, other: Value) -> Value:
        if not self.length or not other.length:
            return self if self.length else other
        out = Value.__new__(Value)
        out.length, out.counts = self.length + other.length, self.counts + other.counts
        if out.length > 1 << 60:  # only doublings get there; the shares of the characters stay, the numbers stay short
            out.counts = Counter({c: max(1, n >> 30) for c, n in out.counts.items()})
            out.length = sum(out.counts.values())
        out.first = (self.first + other.first)[:_REACH] if self.length < _REACH else self.first
        out.last = (self.last + other.last)[-_REACH:] if other.length < _REACH else other.last
        if out.length <= _REACH:
            out.placeholder = bool(_PLACEHOLDER.search(out.first))
        else:  # a part that is one word, or one character again and again, need not be so as a part of more
            inner = _PLACEHOLDER_WORD.search
            out.placeholder = len(out.counts) == 1 or bool(inner(self.last + other.first)) or any(v.placeholder and (v.length > _REACH and len(v.counts) > 1 or bool(inner(v.first))) for v in (self, other))
        return out


def literal_weight(value: Value, quoted: bool) -> float:
    """How much a literal looks like a secret, 0 to 1."""
    if value.length < 8 or value.placeholder:
        return 0.0
    chars, length = value.counts, value.length
    kinds = sum(any(f(c) for c in chars) for f in (str.islower, str.isupper, str.isdigit)) + any(not c.isalnum() for c in chars)
    entropy = -sum(n / length * log2(n / length) for n in chars.values())
    weight = min(1.0, entropy / 4) * min(1.0, length / 12) * (0.4 + 0.2 * kinds)
    if any(c.isspace() for c in chars):
        weight *= 0.3
    return min(1.0, weight) if quoted or (kinds >= 2 and any(c.isdigit() for c in chars)) else 0.0


def pairs(text: str) -> list[tuple[str, list[tuple[str, object]]]]:
    """Name and right side of every assignment; the right side has literals ``("is", (start, end, quoted))`` and names ``("of", name)``."""
    out, closed = [], 0
    for m in _PAIR.finditer(text):
        if m.start() < closed:
            continue  # inside a literal that was read
        at, terms = m.end(), []
        while True:
            if q := _QUOTED.match(text, at):
                g = q.lastindex
                if g:
                    terms.append(("is", (q.start(g), q.end(g), True)))
                at = q.end()
            elif (n := _NAME.match(text, at)) and not (text[n.end() : n.end() + 1] and re.match(r"[\w+/=-]", text[n.end()])):
                terms.append(("of", n[1]))
                if n.end() - n.start() >= 8:
                    terms.append(("is", (n.start(), n.end(), False)))
                at = n.end()
            elif b := _BARE.match(text, at):
                terms.append(("is", (b.start(), b.end(), False)))
                at = b.end()
                break
            else:
                break
            j = _JOIN.match(text, at)
            if not j:
                break
            at = j.end()
        closed = max(closed, at)
        if terms:
            out.append((m[2], terms))
    return out


def resolved(found: list[tuple[str, list]]) -> list[list[int]]:
    """For each assignment those that its right side names: the last before it, or else the first after it."""
    first: dict[str, int] = {}
    for k, (name, _) in enumerate(found):
        first.setdefault(name, k)
    last: dict[str, int] = {}
    out = []
    for k, (name, terms) in enumerate(found):
        out.append([last.get(what, first.get(what, -1)) if kind == "of" else -1 for kind, what in terms])
        last[name] = k
    return out


def values(text: str, found: list[tuple[str, list]], uses: list[list[int]], wanted: list[int]) -> dict[int, Value]:
    """What the ``wanted`` assignments and all that they need stand for; depth first without recursion, loops cut where they close."""
    known: dict[int, Value] = {}
    open_: set[int] = set()
    for start in wanted:
        todo = [start]
        while todo:
            k = todo[-1]
            if k in known:
                todo.pop()
                continue
            need = [] if k in open_ else [j for j in uses[k] if j >= 0 and j not in known and j not in open_]
            open_.add(k)
            if need:
                todo += need
                continue
            whole = Value()
            for (kind, what), j in zip(found[k][1], uses[k], strict=True):
                if kind == "is" and what[2]:
                    whole = whole + Value(text[what[0] : what[1]])
                elif j in known:
                    whole = whole + known[j]
            known[k] = whole
            todo.pop()
    return known


def literal_spans(text: str) -> list[tuple[int, int, str, int]]:
    """Literals that reach a sensitive name, directly or through constants."""
    if ":" not in text and "=" not in text:
        return []
    found = pairs(text)
    own = [name_weight(name) for name, _ in found]
    sensitive = [k for k, w in enumerate(own) if w]
    if not sensitive:
        return []
    uses = resolved(found)
    known = values(text, found, uses, sensitive)
    names = {name for name, _ in found}

    def flow(start: list[tuple[float, int]]) -> dict[int, float]:
        """The largest weight that each assignment is used with: the heaviest go first, so each is reached once."""
        best: dict[int, float] = {}
        for weight, k in sorted(start, reverse=True):
            todo = [k]
            while todo:
                k = todo.pop()
                if k not in best:
                    best[k] = weight
                    todo += [j for j in uses[k] if j >= 0 and j not in best]
        return best

    reach = flow([(own[k], k) for k in sensitive])
    whole = flow([(own[k] * literal_weight(known[k], True), k) for k in sensitive])
    spans = set()
    for k, w in reach.items():
        for kind, what in found[k][1]:
            if kind == "is":
                a, b, quoted = what
                if b - a < 4 or not quoted and text[a:b] in names:
                    continue
                score = w * literal_weight(Value(text[a:b]), quoted)
                if max(score, whole[k] if quoted else 0.0) >= LEAST_SCORE:
                    spans.add((a, b, "literal", a))
    return sorted(spans)


def scan(text: str | None) -> tuple[list, list]:
    """Base spans, and all spans, each ordered by start and kind."""
    if not text:
        return [], []
    order = lambda s: (s[0], KINDS.index(s[2]))
    base = sorted(base_spans(text), key=order)
    runs: list[list[int]] = []  # base spans joined where they touch
    for a, b, *_ in base:
        if runs and a <= runs[-1][1]:
            runs[-1][1] = max(runs[-1][1], b)
        else:
            runs.append([a, b])
    more, k = [], 0
    for s in literal_spans(text):
        while k < len(runs) and runs[k][1] <= s[0]:
            k += 1
        if k == len(runs) or s[0] < runs[k][0] or s[1] > runs[k][1]:
            more.append(s)
    return base, sorted(base + more, key=order)


def redact(text: str | None, mark: str = "[REDACTED]") -> str | None:
    """The text with every found value replaced; a text without findings as it is."""
    values = sorted((v, e) for _, e, _, v in scan(text)[1])
    if not values:
        return text
    out, at = [], 0
    for start, end in values:
        if start >= at:
            out += [text[at:start], mark]
        at = max(at, end)
    return "".join([*out, text[at:]])


def spans_text(spans: list) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, end, kind, _ in spans)


FOUND = "doc_id string, n_assign long, n_access long, n_hex long, n_literal long, base_sha256 string, spans string"


def scan_secrets(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Counts, digest of the base spans and all spans of every row."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for doc_id, whole in zip(batch["_id"], batch["_text"], strict=True):
                base, every = scan(whole)
                n = Counter(s[2] for s in every)
                rows.append((doc_id, *(n[k] for k in KINDS), hashlib.sha256(spans_text(base).encode()).hexdigest(), spans_text(every)))
            yield pd.DataFrame(rows, columns=["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans"])

    # Ids travel as text: a null among them would make pandas hold them as floats.
    found = docs.select(F.col(key).cast("string").alias("_id"), F.col(text).alias("_text")).mapInPandas(run, FOUND)
    return found.withColumn("doc_id", F.col("doc_id").cast("long"))


def redact_secrets(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with the found values replaced in ``text``; ``n_chars``, if there, follows."""

    @F.pandas_udf("string")
    def cleaned(whole: pd.Series) -> pd.Series:
        return whole.map(redact, na_action="ignore")

    # Only texts that may hold a finding go through Python's lexer; the test is a superset of all kinds.
    may = F.col(text).contains(":") | F.col(text).contains("=") | F.col(text).contains("AKIA") | F.col(text).rlike("[0-9a-f]{24}")
    out = docs.withColumn(text, F.when(may, cleaned(F.when(may, F.col(text)))).otherwise(F.col(text)))
    return out.withColumn("n_chars", F.length(text).cast("long")) if "n_chars" in docs.columns else out
