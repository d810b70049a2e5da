"""Secret scanning: fixed patterns, and assignment-aware lexing of source and configuration text.

A lexer tells strings (also triple-quoted and multi-line ones) and comments from code.  A parser reads
name-literal pairs: assignments (``name = "literal"``, ``name := x``, ``name: literal``, ``"name": "literal"``,
``export NAME=literal``), blocks of indented lines after ``name: |``, setters (``setName("literal")``, ``name("literal")``), elements
(``<name>literal</name>``), options (``--name literal``) and passwords of addresses.  Constants are carried
along references and concatenations; a call or a path of names is no literal.  What stands in a comment is
parsed too, but defines no constant of the code.  Each literal is scored by the sensitivity of the name that
it ends up in and by how random it looks.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import pieces, wider

# The base patterns, each with the least length of what it must have found.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")  # a run of 20; a shorter run holds no longer one
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "named")

# Words of names that hold secrets, with their weights, and marks of placeholders.
SENSITIVE = {"password": 1.0, "passwd": 1.0, "pwd": 0.9, "passphrase": 1.0, "secret": 1.0, "token": 0.9, "apikey": 1.0, "credential": 0.9, "credentials": 0.9, "bearer": 0.8, "privatekey": 1.0, "accesskey": 1.0, "auth": 0.6, "signature": 0.5, "salt": 0.6, "key": 0.5}
SETTERS = ("set", "with", "add", "use", "put")
PLACEHOLDERS = ("example", "changeme", "placeholder", "your_", "your-", "xxxx", "****", "dummy", "sample", "redacted")
THRESHOLD = 0.45

QUOTED = r""""([^"\\\n]*(?:\\.[^"\\\n]*)*)"|'([^'\\\n]*(?:\\.[^'\\\n]*)*)'|`([^`\n]*)`"""
TARGET = re.compile(r"""(?<![\w$.-])([A-Za-z_$][A-Za-z0-9_$.-]{0,99}+)["']?[ \t]*+(?::=|=>|=(?!=)|:(?!:|//))[ \t]*""", re.A)
TERM = re.compile(QUOTED + r"""|\$\{?([A-Za-z_]\w*)\}?|([A-Za-z0-9_./+=$@#%&*!-]+)""", re.A)
JOIN = re.compile(r"[ \t]*(?:\+|\.\.)[ \t]*")
PATH = re.compile(r"[A-Za-z_]+(?:\.[A-Za-z_]+)+|\w+(?:\.\w+)*(?=[(\[])", re.A)  # a name, or what is called or looked into
BLOCK = re.compile(r"[|>][+-]?\d?[ \t]*\r?\n")
CALL = re.compile(r"([A-Za-z_$][\w$]{0,99}+)\([ \t]*(?:" + QUOTED + r")[ \t]*[,)]", re.A)
ELEMENT = re.compile(r"<([A-Za-z_][\w.-]{0,99}+)>([^<>\n]{1,4096}+)</([A-Za-z_][\w.-]{0,99}+)>", re.A)
OPTION = re.compile(r"(?<!\S)--([A-Za-z][\w-]{0,99}+)[ \t]+(?:" + QUOTED + r"|([^\s-]\S{0,4095}))", re.A)
ADDRESS = re.compile(r"[A-Za-z][A-Za-z0-9+.-]{0,20}+://[^\s/:@]{1,99}:([^\s/@]{1,200})@", re.A)
OPENERS = re.compile(r"""\"{3}|'{3}|["'`]|/\*|<!--|(?<!:)//|(?<!\S)#""")
CLOSERS = {'"""': '"""', "'''": "'''", "/*": "*/", "<!--": "-->"}
HINTS = re.compile("|".join(sorted({"pass", "pwd", "secret", "token", "key", "credential", "bearer", "auth", "signature", "salt"})), re.I | re.A)
CARRIED = 64  # literals that a name that refers to itself carries on
WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])|\d+", re.A)


def name_weight(name: str) -> float:
    """The largest weight among a name's words, and pairs of them, split at case changes and marks."""
    words = [w.lower() for w in WORDS.findall(name)]
    return max([SENSITIVE.get(w, 0.0) for w in words + [a + b for a, b in zip(words, words[1:])]], default=0.0)


def strength(literal: str) -> float:
    """0 to 1: how much a literal looks like a secret, by length, entropy and character kinds."""
    n = len(literal)
    low = literal.lower()
    if n < 6 or any(p in low for p in PLACEHOLDERS):
        return 0.0
    bits = -sum(c / n * math.log2(c / n) for c in Counter(literal).values())
    kinds = sum(any(f(c) for c in literal) for f in (str.islower, str.isupper, str.isdigit)) + any(not c.isalnum() for c in literal)
    return min(1.0, 0.25 * bits) * (0.4 if kinds == 1 and not literal.isdigit() else 0.8 if kinds == 2 else 1.0)


def lexed(text: str) -> tuple[list[tuple[int, int]], dict[int, int]]:
    """(comments, long strings): spans of comments, and for the place of each triple quote that opens a string where it ends."""
    comments, long, none = [], {}, set()
    at = 0
    while m := OPENERS.search(text, at):
        mark, at = m[0], m.end()
        if mark in CLOSERS:
            if mark in none:  # what is not closed is no opener
                continue
            end = text.find(CLOSERS[mark], at)
            if end < 0:
                none.add(mark)
                continue
            at = end + len(CLOSERS[mark])
            if mark[0] in "\"'":
                long[m.start()] = at
            else:
                comments.append((m.start(), at))
        elif mark in ("//", "#"):
            end = text.find("\n", at)
            at = len(text) if end < 0 else end
            comments.append((m.start(), at))
        elif q := TERM.match(text, m.start()):
            at = max(at, q.end())
    return comments, long


def without(text: str, spans: list[tuple[int, int]]) -> str:
    """``text`` with blanks for all but line feeds in ``spans``."""
    out, last = [], 0
    for a, b in spans:
        out += [text[last:a], re.sub(r"[^\n]", " ", text[a:b])]
        last = b
    return "".join([*out, text[last:]]) if out else text


def indented_block(text: str, name_at: int, at: int) -> int:
    """Where the lines from ``at`` on end that are indented deeper than the line of ``name_at``."""
    start = text.rfind("\n", 0, name_at) + 1
    margin = len(text[start:name_at]) - len(text[start:name_at].lstrip(" \t-"))
    end = at
    while end < len(text):
        stop = text.find("\n", end)
        stop = len(text) if stop < 0 else stop
        line = text[end:stop]
        if line.strip() and len(line) - len(line.lstrip(" \t")) <= margin:
            break
        end = min(len(text), stop + 1)
    return end


def assigned(text: str, long: dict[int, int], known: dict):
    """(name, parts) of each assignment in order, parts as (start, end, literal)."""
    at = 0
    while m := TARGET.search(text, at):
        at = m.end()
        parts: list[tuple[int, int, str]] = []
        referred: set[tuple[int, int]] = set()
        name, pos = m[1], at
        if block := BLOCK.match(text, at):
            for line in re.finditer(r"\S[^\n]*", text[block.end() : indented_block(text, m.start(), block.end())]):
                a = block.end() + line.start()
                parts.append((a, a + len(line[0].rstrip()), line[0].rstrip()))
            yield name, parts
            known[name] = parts[-CARRIED:]
            continue
        while True:
            if pos in long:
                parts.append((pos + 3, long[pos] - 3, text[pos + 3 : long[pos] - 3]))
                pos = at = long[pos]
            elif t := TERM.match(text, pos):
                group = next(i for i in range(1, 6) if t.group(i) is not None)
                word = t[group]
                pos = t.end()
                if group == 4 or group == 5 and word in known:
                    parts += known.get(word, [])
                    referred |= {p[:2] for p in known.get(word, [])}
                elif group == 5 and (p := PATH.match(text, t.start())) and (p.end() >= t.end() or text[p.end() : p.end() + 1] in "(["):
                    break  # of what is called or looked up nothing is known
                else:
                    parts.append((t.start(group), t.end(group), word))
            else:
                break
            j = JOIN.match(text, pos)
            if not j:
                break
            pos = j.end()
        if len(parts) > CARRIED:
            parts = list(dict.fromkeys(parts))
            if any(p[:2] in referred for p in known.get(name, [])):  # a chain of self-references carries its last literals only
                carried = [p for p in parts if p[:2] in referred][-CARRIED:]
                parts = [p for p in parts if p[:2] not in referred or p in carried]
        known[name] = parts
        if parts:
            yield name, parts
        # a quoted or bare value can't hold a further target, but its first word may be one ("a: b: c")
        if text[at : at + 1] in ("'", '"', "`") and (t := TERM.match(text, at)):
            at = max(at, t.end())


def stated(text: str, known: dict):
    """(name, parts) of calls, elements, options and addresses."""
    for m in CALL.finditer(text) if "(" in text else ():
        first = next((w.lower() for w in WORDS.findall(m[1])), "")
        if first not in SETTERS and not name_weight(first):  # what is looked up by a literal does not get it
            continue
        g = next(i for i in (2, 3, 4) if m.group(i) is not None)
        yield m[1], [(*m.span(g), m[g])]
    for m in ELEMENT.finditer(text) if "</" in text else ():
        if m[1] == m[3]:
            yield m[1], [(*m.span(2), m[2])]
    for m in OPTION.finditer(text) if "--" in text else ():
        g = next(i for i in (2, 3, 4, 5) if m.group(i) is not None)
        if not m[g].startswith("$"):
            yield m[1], [(*m.span(g), m[g])]
        elif carried := known.get(m[g].strip("${}")):
            yield m[1], carried
    for m in ADDRESS.finditer(text) if "://" in text else ():
        yield "password", [(*m.span(1), m[1])]


def named_literals(text: str) -> list[tuple[int, int, str, float]]:
    """(start, end, name, score) of literals that reach a sensitive name; at most one entry for a span.

    Statements are read in order; a later value of a name replaces an earlier one.
    """
    if not HINTS.search(text) and "://" not in text:
        return []
    found: dict[tuple[int, int], tuple[str, float]] = {}
    comments, long = lexed(text)
    pieces_ = [(0, without(text, comments), long)] + [(a, text[a:b], {}) for a, b in comments]
    for offset, piece, strings in pieces_:
        known: dict[str, list[tuple[int, int, str]]] = {}
        for source in (assigned(piece, strings, known), stated(piece, known)):
            for name, parts in source:
                weight = name_weight(name)
                score = weight * strength("".join(p[2] for p in parts)) if weight else 0.0
                if score >= THRESHOLD:
                    for a, b, _ in parts:
                        span = (a + offset, b + offset)
                        if b > a and found.get(span, ("", 0.0))[1] < score:
                            found[span] = (name, score)
    return [(a, b, name, score) for (a, b), (name, score) in sorted(found.items())]


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) by the fixed patterns, leftmost and without overlap within a kind."""
    out = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6] if ":" in text or "=" in text else []
    if "AKIA" in text:
        out += [(*m.span(), "access") for m in ACCESS.finditer(text)]
    out += [(*m.span(), "hex") for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


SPAN = "array<struct<kind:string,start:bigint,end:bigint,name:string,score:double>>"


def scan(docs: DataFrame) -> DataFrame:
    """``docs`` with ``secrets``: all spans of each whole ``text`` by start, then kind, in code points.

    A null or empty text has none.  Repeated rows are scanned alike.  Other columns pass through; an
    input column named ``secrets`` is replaced.  Base spans carry score 1 and no name.
    """
    keep = docs.drop("secrets")
    item = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("name", pa.string()), ("score", pa.float64())])

    def run(batches):
        for whole in batches:
            for b in pieces(whole, "text"):
                out = []
                for t in b.column("text").to_pylist():
                    t = t or ""
                    spans = [{"kind": k, "start": s, "end": e, "name": None, "score": 1.0} for s, e, k in base_spans(t)]
                    spans += [{"kind": "named", "start": s, "end": e, "name": n, "score": v} for s, e, n, v in named_literals(t)]
                    out.append(sorted(spans, key=lambda x: (x["start"], KINDS.index(x["kind"]))))
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.list_(item))], names=[*b.schema.names, "secrets"])

    return keep.mapInArrow(run, wider(keep, ("secrets", SPAN)))
