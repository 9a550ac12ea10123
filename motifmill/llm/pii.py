"""Personal data by anchor expansion.

One Aho-Corasick pass over a text finds anchors: at-signs, plus signs, digits,
scheme marks and the cues of identifiers. Small local parsers then walk outward
from each anchor, fix the boundaries of what stands there, and validate it. Texts
without anchors, which are most, cost the one pass.

Base kinds (leftmost, non-overlapping within a kind, failing candidates dropped):
email, ip, card, phone. Added kinds: url (a scheme and what follows it up to white
space or a quote), iban (checked modulo 97), account (a cue and at least six
digits), secret (a cue, an equals sign or colon, and a quoted value of any length
from eight characters, without white space).

Spans are in code points with the end exclusive. Nulls: a null text is empty and has
no spans. Repeated rows are judged each. A very long text is read whole, by the task
that holds its row. An empty table gives an empty result. Other
columns are passed through by ``redact_documents`` and dropped by ``find_pii``.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifmill.llm.words import byte_slices

KINDS = ["email", "ip", "card", "phone", "url", "iban", "account", "secret"]
BASE = KINDS[:4]
# Character classes and cues.
DIGITS = frozenset("0123456789")
LETTERS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz")
LOCAL = LETTERS | DIGITS | frozenset("._%+-")
LABEL = LETTERS | DIGITS | frozenset("-")
PHONE = DIGITS | frozenset(" ().-")
BLANK = frozenset(" \t")
URL_END = frozenset(" \t\n\x0b\x0c\r\"'<>`")
SECRET_END = {q: re.compile(rf"[{q}\s]") for q in "\"'"}
CUES = {"account": ["account", "acct"], "iban": ["iban"], "secret": ["token", "password", "secret", "api_key", "apikey"]}

Span = tuple[str, int, int]


@lru_cache(maxsize=1)
def anchors() -> ahocorasick.Automaton:
    found = ahocorasick.Automaton()
    for mark, kind in [("@", "@"), ("+", "+"), ("://", "url"), *[(d, "digit") for d in DIGITS]]:
        found.add_word(mark, kind)
    for kind, cues in CUES.items():
        for cue in cues:
            for form in {cue, cue.upper(), cue.capitalize()}:
                found.add_word(form, kind)
    found.make_automaton()
    return found


def emails(text: str, ats: list[int]) -> list[Span]:
    out, free = [], 0
    for at in ats:
        start = at
        while start > free and text[start - 1] in LOCAL:
            start -= 1
        end = _run(text, at + 1, LABEL)
        if start == at or end == at + 1:
            continue
        first = end
        while text[end : end + 1] == "." and text[end + 1 : end + 2] in LABEL and end + 1 < len(text):
            end = _run(text, end + 1, LABEL)
        if end > first:
            out.append(("email", start, end))
            free = end
    return out


def _run(text: str, at: int, chars: frozenset) -> int:
    n = len(text)
    while at < n and text[at] in chars:
        at += 1
    return at


def digit_runs(places: list[int]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for p in places:
        if out and out[-1][1] == p:
            out[-1][1] = p + 1
        else:
            out.append([p, p + 1])
    return [(a, b) for a, b in out]


def ips(text: str, runs: list[tuple[int, int]]) -> list[Span]:
    out, k = [], 0
    while k + 3 < len(runs):
        four = runs[k : k + 4]
        if any(x[1] + 1 != y[0] or text[x[1]] != "." for x, y in zip(four, four[1:], strict=False)):
            k += 1
            continue
        parts = [text[a:b].lstrip("0") for a, b in four]
        if all(len(p) < 3 or len(p) == 3 and p <= "255" for p in parts):
            out.append(("ip", four[0][0], four[3][1]))
        k += 4
    return out


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        x = int(d) * (1 + k % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def cards(text: str, runs: list[tuple[int, int]]) -> list[Span]:
    out, k = [], 0
    while k < len(runs):
        j, digits = k, runs[k][1] - runs[k][0]
        while j + 1 < len(runs) and runs[j + 1][0] == runs[j][1] + 1 and text[runs[j][1]] in " -":
            j += 1
            digits += runs[j][1] - runs[j][0]
        if 13 <= digits <= 19 and luhn("".join(text[a:b] for a, b in runs[k : j + 1])):
            out.append(("card", runs[k][0], runs[j][1]))
        k = j + 1
    return out


def phones(text: str, pluses: list[int]) -> list[Span]:
    out = []
    for p in pluses:
        if text[p + 1 : p + 2] not in DIGITS or p + 1 >= len(text):
            continue
        end = _run(text, p + 2, PHONE)
        while end > p + 3 and text[end - 1] not in DIGITS:
            end -= 1
        if end > p + 3 and 9 <= sum(c in DIGITS for c in text[p:end]) <= 15:
            out.append(("phone", p, end))
    return out


def urls(text: str, marks: list[int]) -> list[Span]:
    out, free = [], 0
    for m in marks:
        start = m
        while start > free and text[start - 1] in LETTERS:
            start -= 1
        end = m + 3
        while end < len(text) and text[end] not in URL_END:
            end += 1
        while end > m + 3 and text[end - 1] in ".,;:!?)":
            end -= 1
        if start < m and start >= free and end > m + 3:
            out.append(("url", start, end))
            free = end
    return out


def _value_start(text: str, at: int) -> int:
    """After a cue: blanks, at most one of ``=``, ``:`` and ``#``, blanks."""
    at = _run(text, at, BLANK)
    return _run(text, at + 1, BLANK) if text[at : at + 1] in ("=", ":", "#") else at


def ibans(text: str, ends: list[int]) -> list[Span]:
    out = []
    for e in ends:
        at = stop = _value_start(text, e)
        code = ""
        while stop < len(text) and len(code) < 34 and (text[stop] in LETTERS or text[stop] in DIGITS or text[stop] == " "):
            code += text[stop] if text[stop] != " " else ""
            stop += 1
            if len(code) >= 15 and code[2:4].isdecimal() and int("".join(str(int(c, 36)) for c in code[4:] + code[:4])) % 97 == 1:
                out.append(("iban", at, stop))
                break
    return out


def accounts(text: str, ends: list[int]) -> list[Span]:
    out = []
    for e in ends:
        at = _value_start(text, e)
        stop = _run(text, at, DIGITS | frozenset("-"))
        while stop > at and text[stop - 1] == "-":
            stop -= 1
        if sum(c in DIGITS for c in text[at:stop]) >= 6:
            out.append(("account", at, stop))
    return out


def secrets(text: str, ends: list[int]) -> list[Span]:
    out = []
    for e in ends:
        at = _value_start(text, e)
        if at == e or text[at : at + 1] not in ('"', "'") or at >= len(text):
            continue
        end = SECRET_END[text[at]].search(text, at + 1)  # white space ends a value that has no closing quote
        if end and end[0] == text[at] and end.start() - at > 8:
            out.append(("secret", at + 1, end.start()))
    return out


def text_spans(text: str) -> list[Span]:
    """All spans of a text, by kind in the order of KINDS, then by start."""
    hits: dict[str, list[int]] = {}
    for end, kind in anchors().iter(text):
        hits.setdefault(kind, []).append(end)
    if not hits:
        return []
    runs = digit_runs(hits.get("digit", []))
    after = {k: [e + 1 for e in hits.get(k, [])] for k in CUES}
    return [
        *emails(text, hits.get("@", [])),
        *ips(text, runs),
        *cards(text, runs),
        *phones(text, hits.get("+", [])),
        *urls(text, [e - 2 for e in hits.get("url", [])]),
        *ibans(text, after["iban"]),
        *accounts(text, after["account"]),
        *secrets(text, after["secret"]),
    ]


def redact(text: str, spans: list[Span]) -> str:
    """Each span replaced by its kind in angle brackets; overlapping spans become one, named by the first."""
    out, done = [], 0
    for kind, start, end in sorted(spans, key=lambda s: (s[1], -s[2])):
        if start >= done:
            out += [text[done:start], f"<{kind.upper()}>"]
        done = max(done, end)
    return "".join([*out, text[done:]])


SPANS = "array<struct<kind:string,start:bigint,end:bigint>>"


def find_pii(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(key, spans) of each row."""
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in byte_slices(batches, 1, 4 << 20):
            spans = [text_spans(t) if t else [] for t in batch.column(1).to_pylist()]
            rows = [[{"kind": k, "start": a, "end": b} for k, a, b in x] for x in spans]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, kind)], ["key", "spans"])

    of = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("key"), F.col(text).alias("text")).mapInArrow(run, f"key {of}, spans {SPANS}")


def redact_documents(docs: DataFrame, text: str = "text") -> DataFrame:
    """The rows of ``docs`` with personal data in ``text`` replaced; nulls stay null."""
    names = docs.columns
    at = names.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in byte_slices(batches, at, 4 << 20):
            clean = [t and redact(t, text_spans(t)) for t in batch.column(at).to_pylist()]
            columns = [pa.array(clean, pa.string()) if k == at else c for k, c in enumerate(batch.columns)]
            yield pa.RecordBatch.from_arrays(columns, names)

    return docs.mapInArrow(run, docs.schema)


def spans_text(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts and spans of personal data in every document."""
    found = find_pii(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    count = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    base = F.filter("spans", lambda s: s["kind"].isin(BASE))
    return found.select(
        F.col("key").alias("doc_id"), *[count(k) for k in BASE], F.sha2(spans_text(base), 256).alias("base_sha256"), spans_text(F.col("spans")).alias("spans"),
        *[count(k) for k in KINDS if k not in BASE],
    )
