"""Secret scans: fixed patterns, and guess cost of values in a credential context.

Base kinds, leftmost and non-overlapping each, matches that are too short dropped: assign (a credential word, = or :, a
value of 6 or more), access (AKIA and 16 or more), hex (24 or more hex digits). The method adds kind guess: values that
follow a wider set of credential words and that would take many guesses. The cost of a value is the cheapest way, by
dynamic programming over its positions, to cut it into dictionary words, dates, repeats, keyboard walks, sequences and
brute-force spans, as log10 of the guesses: each span's own guesses multiplied, and as many again as the spans can be
ordered. A value of at least GUESSES is a secret, whatever its length and signs; a word, a date, a walk or a short phrase
of these is not. The dictionary is a fixed list and then the frequent words of all texts, counted in a first pass; a word
in the place of a value counts against itself, so copies of a secret don't make it a word.

Spans are counted in code points, end exclusive, and cover the whole match. A guess span that lies in a
base span is left out; one that reaches further stays beside it. Null and empty texts have none. A value is read as
far as it takes to tell on which side of GUESSES it is.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidied

KINDS = ("assign", "access", "hex", "guess")
GUESSES = 9.0
#: Words taken from the texts (bounds what a task holds), letters of the longest, and words counted before they are sent on.
DICTIONARY, LETTERS, HELD = 1 << 17, 40, 1 << 18
_WORD = re.compile(r"[^\W\d_]{3,}")
_ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I | re.A)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{24,}")
_CONTEXT = re.compile(r"(?<![a-z0-9])(?:pass(?:word|wd|phrase|code)?|pwd|pin|secret|token|api[ _-]?key|access[ _-]?key|private[ _-]?key|auth|bearer|credentials?|login)(?:\x20+is|[\"']?\x20*(?::=|=>|[:=]))\x20*[\"']?([^\s\"'<>]+)", re.I | re.A)
_NEAR = ("pass", "pwd", "pin", "secret", "token", "key", "auth", "bearer", "credential", "login")
#: Frequent passwords and the words of which they are made, most frequent first.
WORDS = ("password 123456 qwerty letmein welcome admin login master dragon monkey football baseball shadow sunshine princess iloveyou trustno "
         "superman batman hello freedom whatever secret test user guest root default changeme example sample dummy none null true false "
         "token key access api code pass word love home work data server prod dev stage temp string value your here the and for with "
         "this that from have you not are was but all can one out day get has him his how man new now old see two way who boy").split()  # fmt: skip
ROWS = ("`1234567890-=", "qwertyuiop[]\\", "asdfghjkl;'", "zxcvbnm,./")
_RANK = {w: i + 1 for i, w in enumerate(WORDS)}
_PLAIN = str.maketrans("@4301!5$7", "aaeoiisst")
_DATE = re.compile(r"(?:19|20)\d\d(?:[-/._]?(?:0[1-9]|1[0-2])(?:[-/._]?(?:0[1-9]|[12]\d|3[01]))?)?|(?:0?[1-9]|[12]\d|3[01])[-/._](?:0?[1-9]|1[0-2])[-/._](?:19|20)?\d\d")


@lru_cache(1)
def _beside() -> dict[str, str]:
    """For each key those that touch it."""
    at = {c: (r, i + 0.5 * (r > 0) + 0.25 * (r > 1) + 0.25 * (r > 2)) for r, row in enumerate(ROWS) for i, c in enumerate(row)}
    return {c: "".join(o for o, (r2, x2) in at.items() if o != c and abs(r - r2) <= 1 and abs(x - x2) <= 1.1) for c, (r, x) in at.items()}


def _alphabet(s: str) -> int:
    return 26 * any("a" <= c <= "z" for c in s) + 26 * any("A" <= c <= "Z" for c in s) + 10 * any("0" <= c <= "9" for c in s) + 33 * any(not c.isalnum() for c in s) or 33


def _spans(value: str, words: dict[str, int]):
    """For each place in turn (end, log10 guesses) of each known pattern that starts there. Runs are followed once."""
    n, low = len(value), value.lower()
    plain = low.translate(_PLAIN)
    same, walk, turns, first, line = [0] * 5, 0, [], 0, 0
    for i in range(n):
        found = []
        for j in range(i + 3, min(n, i + LETTERS) + 1):
            rank = words.get(low[i:j]) or 4 * words.get(plain[i:j], 0)
            if rank:
                part = value[i:j]
                case = 1 if part == low[i:j] else 2 if part[:1].isupper() and part[1:] == low[i + 1 : j] or part.isupper() else 2 ** min(j - i, 8)
                found.append((j, math.log10(rank * case + 1)))
        if (m := _DATE.match(value, i)):
            found.append((m.end(), math.log10(365 * 100)))
        for size in (1, 2, 3, 4):
            e = max(same[size], i)
            while e + size < n and value[e] == value[e + size]:
                e += 1
            same[size], k = e, 1 + (e - i) // size
            if k * size >= 3 and k > 1:
                found.append((i + k * size, size * math.log10(_alphabet(value[i : i + size])) + math.log10(k)))
        if i >= walk:
            first, walk, turns = i, i + 1, [0]
            while walk < n and low[walk] in _beside().get(low[walk - 1], ""):
                turns.append(turns[-1] + (walk > i + 1 and ord(low[walk]) - ord(low[walk - 1]) != ord(low[walk - 1]) - ord(low[walk - 2])))
                walk += 1
        if walk - i >= 3:
            found.append((walk, math.log10(47 * (walk - i)) + min(1 + turns[-1] - turns[i + 1 - first], walk - i) * math.log10(4.6)))
        if i + 1 >= line and i + 1 < n and (step := ord(value[i + 1]) - ord(value[i])) in (1, -1):
            line = i + 2
            while line < n and ord(value[line]) - ord(value[line - 1]) == step and value[line].isalnum():
                line += 1
        if line - i >= 3:
            found.append((line, math.log10(26 * (line - i))))
        yield found


#: log10 of the orders of up to 12 spans. More have over 10**9 orders, so they never make a value cheap.
_ORDERS = [math.log10(math.factorial(k)) for k in range(13)]


def guess_cost(value: str, words: dict[str, int] = _RANK, line: float = math.inf) -> float:
    """log10 of the guesses for the cheapest segmentation of value. With a line, only on which side of it the result
    lies is right, and no more of the value is read than tells that."""
    n, each = len(value), math.log10(max(_alphabet(value), 10))
    if not n:
        return 0.0
    none = [math.inf] * 13
    full = lambda costs: min(c + o for c, o in zip(costs, _ORDERS, strict=True))
    best, brute = [0.0, *none[1:]], none  # by number of spans: up to here; the last one is brute force and may go on
    open_: dict[int, list[float]] = {}  # by end: spans that are not over
    for i, found in enumerate(_spans(value, words)):
        for end, cost in found:
            open_[end] = [min(a, b + cost) for a, b in zip(open_.get(end, none), [math.inf, *best[:12]], strict=True)]
        if found and n in open_ and full(open_[n]) < line < math.inf:
            return full(open_[n])
        brute = [min(a, b) + each for a, b in zip(brute, [math.inf, *best[:12]], strict=True)]
        best = [min(a, b) for a, b in zip(brute, open_.pop(i + 1, none), strict=True)]
        # what any way to the end has cost by now
        if i + 1 < n and (least := min([full(best), *map(full, open_.values())])) >= line:
            return least
    return full(best)


def _in_context(text: str, low: str):
    """Matches of values in a credential context."""
    if ("=" in low or ":" in low or " is " in low) and any(w in low for w in _NEAR):
        yield from _CONTEXT.finditer(text)


def dictionary(docs: DataFrame, text_col: str = "text") -> dict[str, int]:
    """The rank of each known word: WORDS, then by count the words that stand twice or more often outside of values
    than in them."""

    def work(batches):
        seen: Counter[str] = Counter()

        def sent():
            some = [w for w in seen if len(w) <= LETTERS]
            out = pa.RecordBatch.from_arrays([pa.array(some, pa.string()), pa.array([seen[w] for w in some], pa.int64())], names=["word", "n"])
            seen.clear()
            return out

        for batch in batches:
            for text in batch.column(0).to_pylist():
                if text:
                    low = text.lower()
                    seen.update(_WORD.findall(low))
                    for m in _in_context(text, low):
                        for w in _WORD.findall(m.group(1).lower()):
                            seen[w] -= 2
                if len(seen) >= HELD:
                    yield sent()
        yield sent()

    counted = docs.select(F.col(text_col).alias("text")).mapInArrow(tidied(work), "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n")).where("n >= 2")
    ranked = counted.orderBy(F.desc("n"), "word").limit(DICTIONARY).toArrow().column("word").to_pylist()
    return {w: i + 1 for i, w in enumerate(dict.fromkeys([*WORDS, *ranked]))}


def find(text: str, words: dict[str, int] = _RANK) -> list[tuple[str, int, int]]:
    """(kind, start, end) of every span, by start and then kind."""
    low = text.lower()
    out = []
    if "passw" in low or "secret" in low or "token" in low or "key" in low:
        out += [("assign", m.start(), m.end()) for m in _ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        out += [("access", m.start(), m.end()) for m in _ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [("hex", m.start(), m.end()) for m in _HEX.finditer(text)]
    base = list(out)
    for m in _in_context(text, low):
        start, value = m.start(1), m.group(1).rstrip(".,;:!?)]}")
        end = start + len(value)
        if not any(s <= m.start() and end <= e for _, s, e in base) and guess_cost(value, words, GUESSES) >= GUESSES:
            out.append(("guess", m.start(), end))
    return sorted(out, key=lambda x: (x[1], KINDS.index(x[0])))


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


def masked(text: str | None, mark: str = "[SECRET]", words: dict[str, int] = _RANK) -> str | None:
    """The text with every span replaced; spans that touch or overlap make one mark."""
    spans = find(text, words) if text else []
    out, at = [], 0
    for _, s, e in sorted(spans, key=lambda x: x[1:]):
        if s >= at:
            out += [text[at:s], mark]
        at = max(at, e)
    return text if not spans else "".join([*out, text[at:]])


def secret_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, spans array<struct<kind,start,end>>) for every row."""
    held = docs.sparkSession.sparkContext.broadcast(dictionary(docs, text_col))

    def work(batches):
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        for batch in batches:
            rows = [[{"kind": k, "start": s, "end": e} for k, s, e in find(t or "", held.value)] for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, kind)], names=["doc_id", "spans"])

    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tidied(work), "doc_id bigint, spans array<struct<kind:string,start:bigint,end:bigint>>")


def secret_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, n_guess, base_sha256, spans) from secret_spans."""
    shown = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("bigint").alias(f"n_{kind}")
    base = F.filter("spans", lambda s: s["kind"] != "guess")
    return secret_spans(docs, id_col, text_col).select("doc_id", *map(count, KINDS), F.sha2(shown(base), 256).alias("base_sha256"), shown(F.col("spans")).alias("spans"))


def masked_docs(docs: DataFrame, text_col: str = "text", size_col: str = "n_chars") -> DataFrame:
    """docs with secrets masked in the text, and size_col counted anew where the text changed."""
    held = docs.sparkSession.sparkContext.broadcast(dictionary(docs, text_col))

    def work(batches):
        for batch in batches:
            i = batch.schema.get_field_index(text_col)
            before = batch.column(i).to_pylist()
            after = [masked(t, words=held.value) for t in before]
            cols = list(batch.columns)
            cols[i] = pa.array(after, batch.schema.field(i).type)
            if (j := batch.schema.get_field_index(size_col)) >= 0:
                cols[j] = pa.array([n if a == b else len(a) for n, a, b in zip(cols[j].to_pylist(), after, before, strict=True)], batch.schema.field(j).type)
            yield pa.RecordBatch.from_arrays(cols, schema=batch.schema)

    return docs.mapInArrow(tidied(work), docs.schema)
