"""Personal data by anchor expansion.

One Aho-Corasick pass over a text finds anchors: at-signs, plus signs, digits, schemes and identifier cues.  From an
anchor a deterministic parser expands to the boundaries of an email, an IP address, a card, a phone number, an account
number, an IBAN, a login in a URL or a secret that is assigned to a name, and checks it (ranges, digit counts, check
digits).  A parser never looks at a character of its kind twice (runs are possessive), so long runs stay linear.

Null text: empty, no spans.  Matches of a kind don't overlap; those of different kinds may.  Repeated rows get equal
results; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import settled, slices, texts

#: Kinds of the contract, then those that cues add, in the order of output.
BASE = ("email", "ip", "card", "phone")
ADDED = ("account", "iban", "login", "secret")
#: Words before an account number or IBAN.
CUES = ("account no", "account number", "account", "acct", "passport", "ssn", "kontonummer", "konto", "numéro de compte", "cuenta")
#: Ends of the names that a secret is assigned to.
SECRETS = ("token", "secret", "password", "passwd", "pwd", "api_key", "apikey", "api-key", "access_key", "private_key", "secret_key")

LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++").match
IP = re.compile(r"[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++").match
DIGITS = re.compile(r"[0-9]++").match
CARD = re.compile(r"[0-9](?:[ -]?+[0-9])++").match
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]").match
ACCOUNT = re.compile(r"[ \t]*+(?:(?:no|nr|number|nº)\b\.?+[ \t]*+)?+[:#]?+[ \t]*+([0-9](?:[ -]?[0-9]){5,25})(?![0-9])", re.I).match
IBAN = re.compile(r"[ \t]*+[:#]?+[ \t]*+([A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30})(?![A-Za-z0-9])").match
SECRET = re.compile(r"[\"']?+[ \t]*+[=:]=?>?[ \t]*+[\"']?+([A-Za-z0-9+/_=.~-]{16,}+)").match
BEARER = re.compile(r"[ \t]++([A-Za-z0-9+/_=.~-]{16,}+)").match
LOGIN = re.compile(r"[A-Za-z0-9._%+~-]{1,256}:[^\s@/:]{1,256}@[A-Za-z0-9.-]+").match


def automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for c in "0123456789":
        a.add_word(c, ("digit", 1))
    a.add_word("@", ("at", 1))
    a.add_word("+", ("plus", 1))
    a.add_word("://", ("scheme", 3))
    for cue in CUES:
        for form in {cue, cue.upper(), cue.capitalize()}:
            a.add_word(form, ("cue", len(form)))
    a.add_word("IBAN", ("iban", 4))
    for cue in SECRETS:
        for form in {cue, cue.upper(), cue.capitalize()}:
            a.add_word(form, ("secret", len(form)))
    for form in ("bearer", "Bearer", "BEARER"):
        a.add_word(form, ("bearer", 6))
    a.make_automaton()
    return a


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = ord(d) - 48
        total += n if i % 2 == 0 else (2 * n - 9 if n > 4 else 2 * n)
    return total % 10 == 0


def plain(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def iban_ok(s: str) -> bool:
    s = s.replace(" ", "")
    return 15 <= len(s) <= 34 and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


class Finder:
    def __init__(self) -> None:
        self.automaton = automaton()

    def spans(self, text: str) -> dict[str, list[tuple[int, int]]]:
        out: dict[str, list[tuple[int, int]]] = {k: [] for k in BASE + ADDED}
        email = ip = card = phone = account = secret = 0  # where the next match of a kind may start
        for last, (kind, size) in self.automaton.iter(text):
            if kind == "digit":
                if last >= ip:
                    if m := IP(text, last):
                        ip = m.end()
                        if all(len(p.lstrip("0")) < 4 and int(p[-3:]) < 256 for p in m[0].split(".")):
                            out["ip"].append(m.span())
                    else:
                        ip = DIGITS(text, last).end()
                if last >= card:
                    if m := CARD(text, last):
                        card = m.end()
                        if m.end() - m.start() < 40 and 16 <= len(d := plain(m[0])) <= 19 and luhn(d):
                            out["card"].append(m.span())
                    else:
                        card = last + 1
            elif kind == "at":
                start = last
                while start > email and text[start - 1] in LOCAL:
                    start -= 1
                if start < last and (m := DOMAIN(text, last + 1)):
                    email = m.end()
                    out["email"].append((start, email))
                else:
                    email = last + 1
            elif kind == "plus":
                if last >= phone and (m := PHONE(text, last)):
                    phone = m.end()
                    if 8 <= sum("0" <= c <= "9" for c in m[0]) <= 15:
                        out["phone"].append(m.span())
            elif kind == "scheme":
                if m := LOGIN(text, last + 1):
                    start = last - 2
                    while start > 0 and text[start - 1].isalnum():
                        start -= 1
                    out["login"].append((start, m.end()))
            elif kind in ("secret", "bearer"):
                if last >= secret and (m := (SECRET if kind == "secret" else BEARER)(text, last + 1)):
                    secret = m.end()
                    if any("0" <= c <= "9" for c in m[1]) and any(c.isalpha() for c in m[1]):
                        out["secret"].append(m.span(1))
            else:
                before = last - size
                if before >= 0 and text[before].isalnum():
                    continue
                if (m := IBAN(text, last + 1)) and iban_ok(m[1]):
                    if (span := m.span(1)) not in out["iban"][-1:]:
                        out["iban"].append(span)
                elif kind == "cue" and (m := ACCOUNT(text, last + 1)) and m.start(1) >= account:
                    account = m.end(1)
                    out["account"].append(m.span(1))
        return out


def joined(spans: dict[str, list[tuple[int, int]]], kinds: tuple[str, ...]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in kinds for a, b in spans[k])


def redacted(text: str, spans: dict[str, list[tuple[int, int]]]) -> str:
    """The text with every span replaced by its kind in brackets; of overlapping spans, the first to start names the whole."""
    every = sorted((a, b, k) for k, found in spans.items() for a, b in found)
    out, at, i = [], 0, 0
    while i < len(every):
        a, b, k = every[i]
        while i + 1 < len(every) and every[i + 1][0] < b:
            i += 1
            b = max(b, every[i][1])
        out += [text[at:a], f"[{k.upper()}]"]
        at, i = b, i + 1
    return "".join([*out, text[at:]])


def find(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_account, n_iban, n_login, n_secret) of every whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        finder = Finder()
        for b in slices(batches, text_col):
            found = [finder.spans(x) for x in texts(b, text_col)]
            counts = [pa.array([len(f[k]) for f in found], pa.int64()) for k in BASE]
            added = [pa.array([len(f[k]) for f in found], pa.int64()) for k in ADDED]
            base = [hashlib.sha256(joined(f, BASE).encode()).hexdigest() for f in found]
            yield pa.RecordBatch.from_arrays([b.column(0), *counts, pa.array(base, pa.string()), pa.array([joined(f, BASE + ADDED) for f in found], pa.string()), *added], [id_col, *[f"n_{k}" for k in BASE], "base_sha256", "spans", *[f"n_{k}" for k in ADDED]])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(settled(run), f"{id_col} {kind}, {', '.join(f'n_{k} long' for k in BASE)}, base_sha256 string, spans string, {', '.join(f'n_{k} long' for k in ADDED)}")


def redact(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The same rows with personal data in `text_col` replaced; a null text stays null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        finder = Finder()
        for b in slices(batches, text_col):
            new = [None if x is None else redacted(x, finder.spans(x)) for x in b.column(text_col).to_pylist()]
            yield b.set_column(b.schema.get_field_index(text_col), text_col, pa.array(new, b.column(text_col).type))

    return docs.mapInArrow(settled(run), docs.schema)
