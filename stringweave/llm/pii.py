"""Personal data by anchor expansion.

One Aho-Corasick pass over a whole text finds the anchors: at-signs, plus signs,
digits, schemes and identifier cues.  Small deterministic parsers then expand each
anchor to its boundaries and validate it.  The base kinds are ``email``, ``ip``,
``card`` and ``phone``; the method adds ``url`` (an address that carries user
information, or whose host is an IPv4 number) and ``account`` (an identifier after
a cue such as IBAN or account number).  Plain addresses are not personal and are
left alone.

Offsets are code points, the end is exclusive.  A null text is an empty text and
holds no spans.
"""

from __future__ import annotations

import hashlib
import re

import ahocorasick
from pyspark.sql import DataFrame

from stringweave.llm._common import fields, per_text

KINDS = ("email", "ip", "card", "phone", "url", "account")
BASE = 4

# The patterns of the base kinds, expanded from an anchor, and of the added ones.
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+").match
_IP = re.compile(r"[0-9]+(?:\.[0-9]+){3}").match
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+").match
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]").match
_SCHEME = frozenset("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ+.-0123456789")
_AUTHORITY = re.compile(r"[A-Za-z0-9._~%!$&'()*+,;=:@-]+").match
_REST = re.compile(r"[A-Za-z0-9._~%!$&()*+,;=:@/?#-]*").match
_IDENTIFIER = re.compile(r"(?: (?:number|no\.?|nr\.?|#))?[ ]?[:#=]?[ ]?([A-Za-z]{0,2}[0-9](?:[ -]?[A-Za-z0-9]){5,33})(?![A-Za-z0-9])").match
CUES = ("iban", "account", "acct", "passport", "ssn", "social security")


def luhn(digits: str) -> bool:
    """The check sum of card numbers."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def iban_ok(s: str) -> bool:
    """Modulo-97 check of an international account number."""
    s = re.sub(r"[ -]", "", s).upper()
    return 15 <= len(s) <= 34 and s[:2].isalpha() and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def anchors() -> ahocorasick.Automaton:
    """The automaton: at 0, plus 1, digit 2, scheme 3, cue 4."""
    out = ahocorasick.Automaton()
    out.add_word("@", (0, 1))
    out.add_word("+", (1, 1))
    for d in "0123456789":
        out.add_word(d, (2, 1))
    out.add_word("://", (3, 3))
    for cue in CUES:
        for form in {cue, cue.title(), cue.upper(), cue.capitalize()}:
            out.add_word(form, (4, len(form)))
    out.make_automaton()
    return out


def _account(text: str, end: int) -> tuple[int, int] | None:
    m = _IDENTIFIER(text, end)
    if not m:
        return None
    a, b = m.span(1)
    found = m[1]
    # the identifier ends where a plain word begins, as in "12345678 was"
    while (cut := max(found.rfind(" "), found.rfind("-"))) > 0 and not any(c.isdigit() for c in found[cut:]):
        found, b = found[:cut], a + cut
    digits = sum(c.isdigit() for c in found)
    if found[:2].isalpha() and not iban_ok(found) and digits < 7:
        return None
    return (a, b) if digits >= 6 else None


def find(text: str, automaton: ahocorasick.Automaton) -> list[tuple[int, int, int]]:
    """Spans (start, kind, end) in order; of one kind they never overlap."""
    hits: tuple[list, ...] = ([], [], [], [], [])
    for end, (kind, _) in automaton.iter(text):
        hits[kind].append(end)
    ats, pluses, digits, schemes, cues = hits
    out: list[tuple[int, int, int]] = []
    done = 0
    for p in ats:
        a = p
        while a > done and text[a - 1] in _LOCAL:
            a -= 1
        if a < p and (m := _DOMAIN(text, p + 1)):
            done = m.end()
            out.append((a, 0, done))
    ip_done = card_done = 0
    before = -2
    for p in digits:
        if p != before + 1:
            if p >= ip_done and (m := _IP(text, p)):
                ip_done = m.end()
                if all(len(x := part.lstrip("0")) < 4 and int(x or 0) < 256 for part in m[0].split(".")):
                    out.append((p, 1, ip_done))
            if p >= card_done and (m := _CARD(text, p)):
                card_done = m.end()
                bare = m[0].replace(" ", "").replace("-", "")
                if 14 <= len(bare) <= 19 and luhn(bare):
                    out.append((p, 2, card_done))
        before = p
    done = 0
    for p in pluses:
        if p >= done and (m := _PHONE(text, p)):
            done = m.end()
            if 10 <= sum(c.isdigit() for c in m[0]) <= 15:
                out.append((p, 3, done))
    done = 0
    for p in schemes:
        a = p - 2
        while a > done and text[a - 1] in _SCHEME:
            a -= 1
        m = _AUTHORITY(text, p + 1)
        if a >= p - 2 or a < done or not text[a].isalpha() or not m:
            continue
        host = m[0].rpartition("@")[2].partition(":")[0]
        if "@" in m[0] or ((n := _IP(host, 0)) and n.end() == len(host)):
            b = _REST(text, m.end()).end()
            while text[b - 1] in ".,;:!?)":
                b -= 1
            done = b
            out.append((a, 4, b))
    done = 0
    for p in cues:
        if p >= done and (got := _account(text, p + 1)):
            done = got[1]
            out.append((got[0], 5, done))
    out.sort()
    return out


def spell(spans: list[tuple[int, int, int]]) -> str:
    """kind:start:end, joined by commas."""
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def masked(text: str, spans: list[tuple[int, int, int]]) -> str:
    """The text with every run of overlapping spans replaced by its first kind in brackets."""
    out, at = [], 0
    for a, k, b in spans:
        if a >= at:
            out += [text[at:a], f"[{KINDS[k].upper()}]"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def scan(df: DataFrame, text: str = "text", keep: list[str] | None = None, mask: bool = False) -> DataFrame:
    """Append the counts of the base kinds, ``base_sha256``, ``spans`` and, if asked for, ``masked``."""

    def make():
        automaton = anchors()

        def work(texts):
            out: dict[str, list] = {f.name: [] for f in schema}
            for raw in texts:
                t = (raw or b"").decode("utf-8", "replace")
                found = find(t, automaton)
                base = [s for s in found if s[1] < BASE]
                for k in range(BASE):
                    out[f"n_{KINDS[k]}"].append(sum(s[1] == k for s in base))
                out["base_sha256"].append(hashlib.sha256(spell(base).encode()).hexdigest())
                out["spans"].append(spell(found))
                if mask:
                    out["masked"].append(None if raw is None else masked(t, found))
            return out

        return work

    schema = fields("n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string" + (", masked string" if mask else ""))
    return per_text(df, make, schema, text, keep)
