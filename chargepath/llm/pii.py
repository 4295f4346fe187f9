"""Personal data with offset-preserving deobfuscation.

Base detectors run on the source text. Three transducers then rewrite it, each
in one pass from left to right: the first maps homoglyphs and full-width forms
to ASCII and drops invisible characters; the second reads tokens and turns
bracketed, spelled or plain "at" and "dot" into signs where a domain follows;
the third turns spelled digits, and numbers parted by "dot", into digits. Each
output character keeps the source span it came from, so an identifier found in
the rewritten text maps back to source code points. Spans that touch a base
span of the same kind are dropped, so base spans stay as they are. The method
also finds secrets: values assigned to names like token or password, and keys
of known forms.

Null and empty texts give no spans; texts of any length are searched whole, in
time linear in their length; repeated rows give equal results; spans that
start together are ordered by kind; an empty table gives no rows; an output
replaces a column of its name.
"""

import re
from bisect import bisect_left

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chargepath.llm.common import boxed, unboxed

KINDS = ("email", "ip", "card", "phone")
#: Kinds that only the method finds.
MORE_KINDS = ("secret",)
_ORDER = {k: n for n, k in enumerate(KINDS + MORE_KINDS)}
# The contract's patterns, written so that no match is tried twice in a run of digits.
EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
SECRET = re.compile(
    r"""(?i:\b(?:api[_-]?key|access[_-]?key|secret(?:[_-]?key)?|token|password|passwd|pwd)["']?[ \t]{0,8}[=:][ \t]{0,8}["']?)([A-Za-z0-9+/_=.-]{16,})"""
    r"""|\b(AKIA[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36})\b""")
_SECRET_WORDS = ("key", "secret", "token", "passw", "pwd", "akia", "gh")
_HAS_IP = re.compile(r"[0-9]\.[0-9]")
_HAS_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9]){11}")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")

# Look-alike letters and the ASCII letters they stand for.
_CYRILLIC = ("аеорсухіјѕԁАВЕКМНОРСТХІЈЅ", "aeopcyxijsdABEKMHOPCTXIJS")
_GREEK = ("οαρνιΑΒΕΖΗΙΚΜΝΟΡΤΥΧ", "oapviABEZHIKMNOPTYX")
_SIGNS = ("․。｡·‐‑‒–—−    ", "....------    ")
_GLYPHS = {a: b for pair in (_CYRILLIC, _GREEK, _SIGNS) for a, b in zip(*pair, strict=True)}
_GLYPHS |= {chr(c): chr(c - 0xFEE0) for c in range(0xFF01, 0xFF5F)}
_GLYPHS |= {chr(start + k): str(k) for start in (0x0660, 0x06F0, 0x0966, 0x2080) for k in range(10)}
_GLYPHS |= dict.fromkeys("​‌‍⁠﻿­", "")
_ODD = re.compile("[" + "".join(map(re.escape, _GLYPHS)) + "]")
# Spelled digits, and words and signs that stand for at and dot.
_DIGITS = {"zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9"}
#: What a text with spelled numbers holds at least one of.
_SPELLED = (*(f"{w}{c}" for w in _DIGITS for c in " .,-"), "dot")
_AT_WORDS, _DOT_WORDS = frozenset(("at", "arroba")), frozenset(("dot", "punkt", "point", "punto"))
#: Token classes: one letter each.
_WORD, _NUMBER, _DIGIT, _AT, _DOT, _PLUS, _SPACE, _OPEN, _CLOSE, _SIGN_AT, _STOP, _HYPHEN, _COMMA, _OTHER = "WNDAPUSBCMFHKO"
_SIGN_CLASS = {"@": _SIGN_AT, ".": _STOP, "-": _HYPHEN, ",": _COMMA, **dict.fromkeys("[({<", _OPEN), **dict.fromkeys("])}>", _CLOSE)}
_TOKEN = re.compile(r"[A-Za-z]+|[0-9]+|\s+|.", re.S)
_LABEL = frozenset((_WORD, _NUMBER, _DIGIT, _AT, _DOT, _PLUS))
_DIGIT_RUN = re.compile(r"(?<![a-z])(?:zero|oh|one|two|three|four|five|six|seven|eight|nine)[ .,-]+(?:zero|oh|one|two|three|four|five|six|seven|eight|nine|dot|[0-9])|[0-9]\s{0,8}dot\s{0,8}[0-9a-z]")
_BRACKETED = re.compile(r"[\[({<]\s{0,8}(?:at|@|arroba|dot|punkt|point|punto|\.)\s{0,8}[\])}>]")
_SPOKEN = re.compile(r"(?:at|arroba)\s{1,8}[a-z0-9-]{1,63}(?:\.[a-z0-9]|\s{1,8}(?:dot|punkt|point|punto)\s)")
_SPACED = re.compile(r"\s@|@\s")


def _marked(low: str) -> bool:
    """Whether a lower-cased text may hold a disguised at or dot; each look at the text is one fast scan."""
    if any(c in low for c in "[({<") and _BRACKETED.search(low):
        return True
    return bool(("@" in low and _SPACED.search(low)) or _SPOKEN.search(low) or any(f"{s}{w}{t}" in low for w in ("dot", "punkt", "punto") for s in " \n\t" for t in " \n\t"))


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        v = int(c) * (1 + k % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int]]:
    """EMAIL's matches, looked for around each @ only."""
    out, done, at = [], 0, text.find("@")
    while at >= 0:
        lo = at
        while lo > done and text[lo - 1] in _LOCAL:
            lo -= 1
        found = EMAIL.match(text, lo) if lo < at else None
        if found:
            out.append(found.span())
            done = found.end()
        at = text.find("@", max(done, at + 1))
    return out


def detect(text: str) -> list[tuple[str, int, int]]:
    """The base spans of a text, by start, then by kind."""
    out = [("email", *s) for s in emails(text)] if "@" in text else []
    if _HAS_IP.search(text):
        out += [("ip", *m.span()) for m in IP.finditer(text) if all(len(p) < 4 and int(p or 0) < 256 for p in (q.lstrip("0") for q in m[0].split(".")))]
    if _HAS_CARD.search(text):
        for m in CARD.finditer(text):
            if m.end() - m.start() < 38:
                digits = m[0].replace(" ", "").replace("-", "")
                if 12 <= len(digits) <= 19 and luhn(digits):
                    out.append(("card", *m.span()))
    if "+" in text:
        out += [("phone", *m.span()) for m in PHONE.finditer(text) if 9 <= sum(c.isdigit() for c in m[0]) <= 15]
    return sorted(out, key=lambda s: (s[1], _ORDER[s[0]]))


def secrets(text: str, low: str) -> list[tuple[str, int, int]]:
    """Secrets of a text, whose lower-cased form tells whether to look."""
    return [("secret", *m.span(m.lastindex)) for m in SECRET.finditer(text)] if any(w in low for w in _SECRET_WORDS) else []


class Rewriter:
    """A text and, for each of its characters, the source span it came from."""

    def __init__(self, text: str) -> None:
        self.text, self.starts, self.ends = text, None, None

    def apply(self, edits: list[tuple[int, int, str]]) -> None:
        """edits: (start, end, by) in the present text, in order and apart."""
        if not edits:
            return
        starts = self.starts or range(len(self.text))
        ends = self.ends or range(1, len(self.text) + 1)
        text, new_starts, new_ends, at = [], [], [], 0
        for lo, hi, by in edits:
            text.append(self.text[at:lo])
            new_starts += starts[at:lo]
            new_ends += ends[at:lo]
            text.append(by)
            new_starts += [starts[lo]] * len(by)
            new_ends += [ends[hi - 1]] * len(by)
            at = hi
        text.append(self.text[at:])
        self.text, self.starts, self.ends = "".join(text), [*new_starts, *starts[at:]], [*new_ends, *ends[at:]]


def tokens(text: str) -> tuple[str, list[int], list[str]]:
    """(class of each token as one string, where tokens start and the last ends, lower-cased tokens)."""
    kinds, starts, words = [], [], []
    for m in _TOKEN.finditer(text):
        w = m[0].lower()
        c = w[0]
        if "a" <= c <= "z":
            kind = _DIGIT if w in _DIGITS else _AT if w in _AT_WORDS else _DOT if w in _DOT_WORDS else _PLUS if w == "plus" else _WORD
        else:
            kind = _NUMBER if "0" <= c <= "9" else _SPACE if c.isspace() else _SIGN_CLASS.get(c, _OTHER)
        kinds.append(kind)
        starts.append(m.start())
        words.append(w)
    return "".join(kinds), [*starts, len(text)], words


def _mark(kinds: str, k: int, signs: str, spelled: str) -> tuple[int, bool] | None:
    """(end, whether it has brackets) of a disguised sign that starts at token k: S?BS?xS?CS?, SxS with a word, or x beside a space."""
    at = k
    if kinds.startswith(_SPACE, at):
        at += 1
    if kinds.startswith(_OPEN, at):
        at += 1
        at += kinds.startswith(_SPACE, at)
        if kinds[at : at + 1] not in (*signs, *spelled):
            return None
        at += 1
        at += kinds.startswith(_SPACE, at)
        if not kinds.startswith(_CLOSE, at):
            return None
        at += 1
        return at + kinds.startswith(_SPACE, at), True
    here = kinds[at : at + 1]
    if here and here in spelled and at > k and kinds.startswith(_SPACE, at + 1):
        return at + 2, False
    if here == _SIGN_AT and here in signs and (at > k or kinds.startswith(_SPACE, at + 1)):
        return at + 1 + kinds.startswith(_SPACE, at + 1), False
    return None


def signs(text: str) -> list[tuple[int, int, str]]:
    """Edits of the second transducer.

    Its states: outside; after a label; in a domain, with the edits that wait
    for it. A bracketed sign is written at once. A spelled or spaced "at" waits
    until a domain of two labels or more, the last of letters only, has been
    read, and so do the spelled dots of the domain. Each token is read a
    bounded number of times.
    """
    kinds, at, words = tokens(text)
    out, wait, k = [], [], 0
    state, dots, sure = "out", 0, False

    def settle() -> None:
        nonlocal wait, dots, sure, state
        if wait and (sure or (dots and state == "label" and len(last) > 1 and last.isalpha())):
            out.extend(wait)
        wait, dots, sure = [], 0, False

    last, domain = "", False
    while k < len(kinds):
        kind = kinds[k]
        if kind in _LABEL and state != "label":
            last, state, k = words[k], "label", k + 1
            continue
        if state == "label":
            if kind in _LABEL or kind == _HYPHEN:
                last, k = last + words[k], k + 1
                continue
            if not domain and (mark := _mark(kinds, k, _SIGN_AT, _AT)):
                settle()
                wait, sure, domain, state = [(at[k], at[mark[0]], "@")], mark[1], True, "sign"
                k = mark[0]
                continue
            if not domain and kind == _SIGN_AT:
                settle()
                domain, state, k = True, "sign", k + 1
                sure = True
                continue
            if mark := _mark(kinds, k, _STOP, _DOT):
                if domain or mark[1]:
                    sure = sure or (mark[1] and not domain)
                    wait.append((at[k], at[mark[0]], "."))
                    dots, state, k = dots + 1, "sign", mark[0]
                    continue
            if kind == _STOP and k + 1 < len(kinds) and kinds[k + 1] in _LABEL:
                dots, state, k = dots + 1, "sign", k + 1
                continue
        settle()
        state, domain, k = "out", False, k + 1
    settle()
    return out


def digits(text: str) -> list[tuple[int, int, str]]:
    """Edits of the third transducer.

    Its states: outside, after a plus, after a digit, after a separator, after
    a dot word. A run ends with its last digit; it is rewritten if a word in it
    is spelled and seven characters or more come out.
    """
    kinds, at, words = tokens(text)
    step = {("out", _PLUS): "plus", ("plus", _SPACE): "plus", ("plus", _HYPHEN): "plus", ("part", _DOT): "dot", ("digit", _DOT): "dot", ("dot", _SPACE): "dot", ("dot", _HYPHEN): "dot"}
    step |= {(s, d): "digit" for s in ("out", "plus", "part", "dot") for d in (_DIGIT, _NUMBER)}
    step |= {(s, x): "part" for s in ("digit", "part") for x in (_SPACE, _HYPHEN, _COMMA, _STOP)}
    out, k = [], 0
    while k < len(kinds):
        if ("out", kinds[k]) not in step or (k and kinds[k - 1] in _LABEL):
            k += 1
            continue
        start, end, state = k, k, "out"
        while k < len(kinds) and (to := step.get((state, kinds[k]))):
            state, k = to, k + 1
            if state == "digit":
                end = k
        while end > start and end < len(kinds) and kinds[end] in _LABEL:  # letters go on: the last number is no digit
            end -= 1
            while end > start and kinds[end - 1] not in (_DIGIT, _NUMBER):
                end -= 1
        run = kinds[start:end]
        if _DIGIT in run or _DOT in run:
            stop = "" if _DOT in run else "."
            by = "".join("+" if c == _PLUS else _DIGITS[w] if c == _DIGIT else w if c == _NUMBER else "." if c == _DOT else stop if c == _STOP else "" for c, w in zip(run, words[start:end], strict=True))
            if len(by) >= 7:
                out.append((at[start], at[end], by))
    return out


def deobfuscate(text: str) -> Rewriter | None:
    """The rewritten text, or None if nothing in it is disguised."""
    out = Rewriter(text)
    if not text.isascii():
        out.apply([(*m.span(), _GLYPHS[m[0]]) for m in _ODD.finditer(text)])
    if _marked(out.text.lower()):
        out.apply(signs(out.text))
    low = out.text.lower()
    if any(w in low for w in _SPELLED) and _DIGIT_RUN.search(low):
        out.apply(digits(out.text))
    return out if out.starts is not None else None


def spans(text: str) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
    """(base spans, all spans) of a text in source code points."""
    base, more = detect(text), secrets(text, text.lower())
    out = deobfuscate(text)
    if out is not None:
        known = {k: [s for s in base if s[0] == k] for k in KINDS}
        ends = {k: [s[2] for s in known[k]] for k in KINDS}  # spans of a kind don't overlap, so ends ascend
        done = dict.fromkeys(KINDS, 0)
        for kind, lo, hi in detect(out.text):
            lo, hi = out.starts[lo], out.ends[hi - 1]
            at = bisect_left(ends[kind], lo + 1)
            if lo >= done[kind] and not (at < len(ends[kind]) and known[kind][at][1] < hi):
                more.append((kind, lo, hi))
                done[kind] = hi
    return base, sorted(base + more, key=lambda s: (s[1], _ORDER[s[0]])) if more else base


def masked(text: str, found: list[tuple[str, int, int]]) -> str:
    """text with spans replaced by <KIND>; of overlapping spans the union, named by its first."""
    merged: list[list] = []
    for kind, lo, hi in found:
        if merged and lo < merged[-1][2]:
            merged[-1][2] = max(hi, merged[-1][2])
        else:
            merged.append([kind, lo, hi])
    out, at = [], 0
    for kind, lo, hi in merged:
        out += [text[at:lo], f"<{kind.upper()}>"]
        at = hi
    return "".join([*out, text[at:]])


def _joined(found) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in found)


def _joined(found) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in found)


def find_pii(docs: DataFrame, mask: bool = False) -> DataFrame:
    """docs -> docs + base_spans, spans (strings kind:start:end, comma-joined) [, masked text]."""

    @F.pandas_udf("base_spans string, spans string, masked string")
    def found(texts: pd.Series) -> pd.DataFrame:
        rows = []
        for t in texts:
            base, every = spans(t or "")
            rows.append((_joined(base), _joined(every), masked(t, every) if mask and every else None))
        return pd.DataFrame(rows, columns=["base_spans", "spans", "masked"])

    rows = boxed(docs, text=F.col("text"))
    rows = rows.select("row", "text", found("text").alias("pii"))
    outputs = {"base_spans": F.col("pii.base_spans"), "spans": F.col("pii.spans")}
    if mask:
        outputs["masked"] = F.when(F.col("pii.spans") != "", F.col("pii.masked")).otherwise(F.col("text"))
    return unboxed(rows, **outputs)


def counts(base_spans):
    """(n_email, n_ip, n_card, n_phone) of a span string."""
    return [F.regexp_count(base_spans, F.lit(f"{k}:")).cast("long").alias(f"n_{k}") for k in KINDS]


__all__ = ["KINDS", "MORE_KINDS", "counts", "deobfuscate", "detect", "find_pii", "masked", "spans"]
