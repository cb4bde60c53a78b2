"""Secret scans: base patterns, and assignment-aware lexing of source and configuration syntax.

Base kinds are patterns: ``assign`` (a sensitive word, a sign and a value of six or more characters),
``access`` (AKIA keys) and ``hex`` (24 or more hexadecimal digits).

The lexer visits every assignment sign of the text (``=``, ``:``, ``:=``, ``=>``), wherever it stands in a line: after a separator,
a bracket, a dash, modifiers or a type. The target is the name before the sign (quoted, or with an index or ``[]``, or not), and the value is made of string
literals, names and concatenations of both; a literal that is a value is one token, so signs in it do not count. ``a = b = value`` and
``name: type = value`` give the value to each name. Constants are propagated in order of the text: a name stands for the literals
assigned to it last, so a literal reaches every target that it flows into, however many there are. A literal is scored by the most sensitive
name that it flows into, plus its length and variety, and is reported as kind ``literal`` at ``MIN_SCORE`` or more,
unless a base span covers it. Base spans always stay.

Whole texts are scanned, one text at a time; nothing is shuffled.

Defined cases: null and empty texts have no spans; ties (spans of one start) are ordered as the kinds are
listed; repeated rows are scanned each; extra columns are not read; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KINDS = ("assign", "access", "hex", "literal")
MIN_SCORE = 5

_ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{24,}")
#: A text without any of these in lower case has no assign match.
_HINTS = ("passw", "secret", "token", "api")

#: Sensitive parts of target names and what they weigh.
SENSITIVE = {
    "password": 4, "passwd": 4, "passphrase": 4, "pwd": 4, "secret": 4, "token": 3, "apikey": 4, "accesskey": 4,
    "privatekey": 4, "credential": 4, "credentials": 4, "auth": 2, "signature": 2, "key": 2,
}

_SIGN = re.compile(r"(?<![=:!<>])(?P<sign>:=|=>|[:=])(?![=:/])")
_NAME_CHARS = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789_.-"
_INDEX = re.compile(r"""\[[^\[\]\n"']*\]\Z""")
#: What may stand between the sign of a name and a second one: another target, or a type.
_BETWEEN = re.compile(r"""[\x20\t]*[&*]?[A-Za-z_][A-Za-z0-9_.]*+(?:[\x20\t]*[<\[][^=:;\n"]*[>\]])?(?:[\x20\t]*\|[\x20\t]*[A-Za-z_]++)*[\x20\t]*[?*&]?[\x20\t]*""", re.A)
_TYPES = frozenset("str string text char varchar bytes any object optional option union final null none undefined".split())
_ATOM = re.compile(r"""[\x20\t]*(?:"((?:[^"\\\n]|\\.)*)"|'((?:[^'\\\n]|\\.)*)'|([A-Za-z_][A-Za-z0-9_.-]*))""", re.A)
_PLUS = re.compile(r"[\x20\t]*[+.&][\x20\t]*")
_BARE = re.compile(r"[A-Za-z0-9+/_.=~!@%^*-]+", re.A)


def base_spans(text: str) -> list[tuple[int, int, str]]:
    found = []
    low = text.lower()
    if any(h in low for h in _HINTS):
        found += [(m.start(), m.end(), "assign") for m in _ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        found += [(m.start(), m.end(), "access") for m in _ACCESS.finditer(text) if m.end() - m.start() >= 20]
    found += [(m.start(), m.end(), "hex") for m in _HEX.finditer(text)]
    return found


def name_parts(name: str) -> list[str]:
    """The words of a name in snake, kebab, dotted or camel case, and pairs of neighbours joined."""
    words = [w.lower() for w in re.findall(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|\d+", name)]
    return words + [a + b for a, b in zip(words, words[1:])]


def name_score(name: str) -> int:
    return max((SENSITIVE.get(p, 0) for p in name_parts(name)), default=0)


def literal_score(value: str) -> int:
    """0 to 4 points for length and variety; text of several words has none."""
    if len(value) < 6 or re.search(r"\s", value):
        return 0
    classes = sum(bool(re.search(c, value)) for c in ("[a-z]", "[A-Z]", "[0-9]", "[^A-Za-z0-9]"))
    return 1 + (len(value) >= 12) + (classes >= 2) + (classes >= 3)


def target(before: str) -> str:
    """The name that ends ``before``, without its quotes and index; '' for none."""
    before = before.rstrip(" \t")
    if before.endswith("]"):
        index = _INDEX.search(before, before.rfind("["))
        before = before[: index.start()] if index else before[:-1]
        before = before.rstrip(" \t")
    if before.endswith(('"', "'")):
        before = before[:-1]
    return before[len(before.rstrip(_NAME_CHARS)) :].lstrip("0123456789.-")


def _value(text: str, at: int, sign: str) -> tuple[list[tuple[str | None, tuple[int, int]]], int]:
    """Parts of the value at a place, and where it ends."""
    parts: list[tuple[str | None, tuple[int, int]]] = []
    while a := _ATOM.match(text, at):
        group = a.lastindex
        if group == 3 and not parts and sign in (":", "=") and not _PLUS.match(text, a.end()):
            bare = _BARE.match(text, a.start(3))
            if bare and bare[0] != a[3]:  # an unquoted value, not a name
                return [(None, bare.span())], bare.end()
        parts.append((a[3] if group == 3 else None, a.span(group)))
        at = a.end()
        if not (p := _PLUS.match(text, at)):
            break
        at = p.end()
    if not parts:
        while text[at : at + 1] in (" ", "\t"):
            at += 1
        if bare := _BARE.match(text, at):
            return [(None, bare.span())], bare.end()
    return parts, at


def assignments(text: str) -> Iterator[tuple[list[str], list[tuple[str | None, tuple[int, int]]]]]:
    """Targets with the parts of their values: (None, span) for a literal, (name, span) for what may stand for another."""
    at = last = 0
    held: tuple[list[str], list, int, str] | None = None  # targets whose value may prove to be a target or type
    while m := _SIGN.search(text, at):
        name, names = target(text[last : m.start()]), []
        if held:
            if m["sign"] in ("=", ":=") and _BETWEEN.fullmatch(text, held[2], m.start()):
                names = held[0]
                if held[3] == ":" and name.lower() in _TYPES:
                    name = ""
            elif held[1]:
                yield held[0], held[1]
            held = None
        names = names + [name] if name else names
        at = last = m.end()
        if not names:
            continue
        parts, end = _value(text, at, m["sign"])
        if any(part is None for part, _ in parts):
            yield names, parts
            at = last = end
            # A bare value may hold another assignment, as in ``a=b=x``.
            start, stop = parts[0][1]
            if stop == end and "=" in text[start:end]:
                at = last = start
        else:
            held = names, parts, m.end(), m["sign"]
    if held and held[1]:
        yield held[0], held[1]


def lexed_spans(text: str) -> list[tuple[int, int, str]]:
    """Literals that flow into sensitive names. An unquoted word that nothing was assigned to is a literal only where it is the whole value and has a digit."""
    if "=" not in text and ":" not in text:
        return []
    known: dict[str, int] = {}
    weights: list[int] = []
    sources: list[list[int | tuple[int, int]]] = []
    for names, parts in assignments(text):
        # A source is a literal's span or the number of the assignment that a name stands for.
        found = [at if part is None else known[part] for part, at in parts if part is None or part in known]
        if len(parts) == 1 and not found and re.search("[0-9]", parts[0][0]):
            found.append(parts[0][1])
        for name in names:
            known[name] = len(weights)
        weights.append(max(map(name_score, names)))
        sources.append(found)
    best: Counter[tuple[int, int]] = Counter()
    # Sources come before what they flow into, so one pass from the end carries the weights to the literals.
    for i in range(len(sources) - 1, -1, -1):
        for x in sources[i]:
            if isinstance(x, int):
                weights[x] = max(weights[x], weights[i])
            else:
                best[x] = max(best[x], weights[i])
    return [(a, b, "literal") for (a, b), weight in best.items() if weight and (points := literal_score(text[a:b])) and weight + points >= MIN_SCORE]


def all_spans(text: str) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str]]]:
    """Base spans, and all spans; each by start, then as the kinds are listed."""
    order = lambda s: (s[0], KINDS.index(s[2]), s[1])
    base = sorted(base_spans(text), key=order)
    added = [s for s in lexed_spans(text) if not any(b[0] < s[1] and s[0] < b[1] for b in base)]
    return base, sorted(base + added, key=order)


def _joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for a, b, kind in spans)


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, n_assign, n_access, n_hex, base_sha256, spans, n_literal. Spans are ``kind:start:end`` in code points."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for i in range(batch.num_rows):
                base, spans = all_spans(batch.column(1)[i].as_py() or "")
                n = Counter(s[2] for s in spans)
                out.append((n["assign"], n["access"], n["hex"], hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(spans), n["literal"]))
            columns = list(zip(*out)) or [()] * 6
            types = [pa.int64()] * 3 + [pa.string()] * 2 + [pa.int64()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(c, t) for c, t in zip(columns, types))],
                ["id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_literal"],
            )

    found = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col)).mapInArrow(
        rows, "id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_literal long"
    )
    return found.withColumnRenamed("id", id_col)
