"""Personal data by anchor expansion.

One Aho-Corasick automaton finds anchors: at-signs, plus signs, scheme marks, digits and identifier
cues. From each anchor a deterministic local parser expands to the boundaries and validates: an address
leftwards and rightwards from its at-sign, a number from its first digit. No pattern is searched for
over the whole text.

Kinds. Base: email, ip, card, phone. The method adds: url (a scheme mark with letters before it and a
host with a dot or port after it, and user data or a query), spelled (an address written with [at] and
[dot]), iban (two letters, two digits, 11 to 30 more, remainder 1 modulo 97), account (a cue such as
"account" or "passport", then an identifier of 5 to 24 letters and digits with at least 4 digits).

Null or empty texts: no spans. Offsets are code points, ends exclusive. Spans of one kind do not
overlap; spans of two kinds may. Repeated rows and ids: one row each.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import documents, kept_in_worker

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "url", "spelled", "iban", "account")
SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long"
#: Identifier cues, lower case.
CUES = ("account", "acct", "iban", "passport", "ssn", "routing", "customer id", "member id", "tax id", "license no")
SPELLED = ("[at]", "(at)")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
LETTERS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz")
DIGITS = frozenset("0123456789")


class Anchors:
    """The automaton and the parsers that start at its hits."""

    def __init__(self):
        import ahocorasick

        auto = ahocorasick.Automaton()
        for word, kind in [("@", "@"), ("+", "+"), ("://", "url"), *((d, "digit") for d in "0123456789"), *((c, "cue") for c in CUES), *((c, "spelled") for c in SPELLED)]:
            auto.add_word(word, (kind, len(word)))
        auto.make_automaton()
        self.hits = auto.iter
        self.domain = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+").match
        self.quad = re.compile(r"([0-9]+)\.([0-9]+)\.([0-9]+)\.([0-9]+)").match
        self.digits = re.compile(r"[0-9](?:[\x20-]?[0-9])+").match
        self.dialled = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]").match
        self.url = re.compile(r"://(?:[^\s/?#@<>\"]+@)?[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*(?::[0-9]{1,5})?(?:[/?#][^\s<>\"]*)?").match
        self.dotted = re.compile(r"[\x20]?[A-Za-z0-9-]+(?:[\x20]?(?:\[dot\]|\(dot\))[\x20]?[A-Za-z0-9-]+)+").match
        self.after_cue = re.compile(r"(?:[\x20]*(?:number|no\.?|nr\.?|#|id))?[\x20]*[:=#]?[\x20]*", re.I).match
        self.ident = re.compile(r"[A-Za-z0-9](?:-?[A-Za-z0-9]){4,23}(?![A-Za-z0-9])").match
        self.iban = re.compile(r"[A-Z]{2}[0-9]{2}(?:[\x20]?[A-Z0-9]){11,30}(?![A-Za-z0-9])").match

    def spans(self, text: str | None) -> list[tuple[int, int, int]]:
        """(start, rank of the kind, end), sorted."""
        if not text:
            return []
        out: list[tuple[int, int, int]] = []
        end_of = [0] * len(KINDS)
        folded = text.lower()
        if len(folded) != len(text):  # a letter whose lower case is longer: fold ASCII only
            folded = "".join(c.lower() if c.isascii() else c for c in text)
        run_end = 0
        for last, (kind, n) in self.hits(folded):
            at = last - n + 1
            if kind == "digit":
                if at < run_end:
                    continue
                run_end = at + 1
                while run_end < len(text) and text[run_end] in DIGITS:
                    run_end += 1
                self._number(text, at, run_end, out, end_of)
            elif kind == "@":
                self._email(text, at, out, end_of)
            elif kind == "+":
                if at >= end_of[3] and (m := self.dialled(text, at)):
                    end_of[3] = m.end()
                    if 10 <= sum(c in DIGITS for c in m[0]) <= 15:
                        out.append((at, 3, m.end()))
            elif kind == "url":
                self._url(text, at, out, end_of)
            elif kind == "spelled":
                self._spelled(text, folded, at, n, out, end_of)
            else:
                self._cued(text, at, at + n, out, end_of)
        out.sort()
        return out

    def _email(self, text, at, out, end_of):
        start = at
        while start > end_of[0] and text[start - 1] in LOCAL:
            start -= 1
        if start < at and (m := self.domain(text, at + 1)):
            end_of[0] = m.end()
            out.append((start, 0, m.end()))

    def _number(self, text, at, run_end, out, end_of):
        follow = text[run_end : run_end + 1]
        if at >= end_of[1] and follow == "." and (m := self.quad(text, at)):
            end_of[1] = m.end()
            if all(len(p) <= 3 and int(p or 0) <= 255 for p in (g.lstrip("0") for g in m.groups())):
                out.append((at, 1, m.end()))
        # A card may start inside a run only where the last one ended, which is at a run's end.
        if at >= end_of[2] and (run_end - at > 1 or follow in (" ", "-")) and (m := self.digits(text, at)):
            end_of[2] = m.end()
            if m.end() - at >= 14:
                number = [ord(c) - 48 for c in m[0] if c in DIGITS]
                if 14 <= len(number) <= 19 and luhn(number):
                    out.append((at, 2, m.end()))
        if run_end - at >= 2 and at >= 2 and text[at - 1] in LETTERS and text[at - 2] in LETTERS and (at < 3 or not text[at - 3].isalnum()) and at - 2 >= end_of[6] and (m := self.iban(text, at - 2)):
            number = m[0].replace(" ", "")
            if int("".join(str(int(c, 36)) for c in number[4:] + number[:4])) % 97 == 1:
                end_of[6] = m.end()
                out.append((at - 2, 6, m.end()))

    def _url(self, text, at, out, end_of):
        start = at
        while start > end_of[4] and text[start - 1] in LETTERS:
            start -= 1
        if start < at and (m := self.url(text, at)) and ("@" in m[0] or "?" in m[0]):
            end = m.end()
            while text[end - 1] in ".,;:!?)":
                end -= 1
            end_of[4] = end
            out.append((start, 4, end))

    def _spelled(self, text, folded, at, n, out, end_of):
        stop = at - 1 if at and text[at - 1] == " " else at
        start = stop
        while start > end_of[5] and text[start - 1] in LOCAL:
            start -= 1
        if start < stop and (m := self.dotted(folded, at + n)):
            end_of[5] = m.end()
            out.append((start, 5, m.end()))

    def _cued(self, text, at, end, out, end_of):
        if at and text[at - 1].isalnum():
            return
        m = self.ident(text, self.after_cue(text, end).end())
        if m and m.start() > end and m.start() >= end_of[7] and sum(c in DIGITS for c in m[0]) >= 4:
            end_of[7] = m.end()
            out.append((m.start(), 7, m.end()))


def luhn(number: list[int]) -> bool:
    back = number[::-1]
    return (sum(back[::2]) + sum(d * 2 - 9 * (d > 4) for d in back[1::2])) % 10 == 0


def row(text: str | None, anchors: Anchors) -> tuple:
    spans = anchors.spans(text)
    n = [0] * len(KINDS)
    for _, k, _ in spans:
        n[k] += 1
    name = lambda s: f"{KINDS[s[1]]}:{s[0]}:{s[2]}"
    base = ",".join(name(s) for s in spans if s[1] < len(BASE))
    return *n[:4], hashlib.sha256(base.encode()).hexdigest(), ",".join(map(name, spans)), len(spans)


def find(docs: DataFrame) -> DataFrame:
    """Spans of each document (doc_id, text)."""

    def run(batches):
        anchors = kept_in_worker("pii", Anchors)
        for b in batches:
            cols = list(zip(*(row(t, anchors) for t in b.column(1).to_pylist()))) or [()] * 7
            kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.int64()]
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), *(pa.array(c, k) for c, k in zip(cols, kinds))], names=[x.split()[0] for x in SCHEMA.split(", ")])

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA)


def masked_text(text: str | None, anchors: Anchors | None = None) -> str | None:
    """The text with each span replaced by its kind; of overlapping spans the first counts."""
    if not text:
        return text
    out, at = [], 0
    for a, k, b in (anchors or Anchors()).spans(text):
        if a >= at:
            out += [text[at:a], f"<{KINDS[k]}>"]
            at = b
    return "".join([*out, text[at:]])


def op3_anchor_expansion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find(documents(spark, sf_dir))
