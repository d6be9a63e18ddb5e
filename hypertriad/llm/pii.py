"""Personal data: exact base patterns, and a semi-Markov conditional random field that adds spans.

The field scores whole segments: features see a candidate's shape, digits, checksums, words of names and streets, the cue
before it and its neighbours at once, and a dynamic programme over segments of at most MAX_TOKENS tokens chooses boundaries
and kinds together.  A segment of another kind than "outside" must hold a trigger (a digit, an at sign or a given name) or
follow a cue for secrets or persons, and a token outside scores 0, so the programme splits exactly into windows round
triggers and cues.  Base matches are fixed segments: the field never removes or overlaps one.  It is trained here by maximum
likelihood on sentences made by a seeded generator.
"""

from __future__ import annotations

import hashlib
import random
import re
from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh

BASE = ("email", "ip", "card", "phone")
KINDS = ("outside", *BASE, "secret", "national_id", "iban", "person", "address", "birth_date")
MAX_TOKENS = 12

_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = re.compile(r"[A-Za-z0-9._%+-]*\Z")
_LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_CHAIN = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++)+")  # no backtracking into long runs of digits
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
# Common given names, words that end or begin the name of a street, months, and cues of English, German, French
# and Spanish.
GIVEN = frozenset("John Mary James Anna Robert Maria Michael Peter Paul David Laura Sarah Thomas Emma Daniel Sophie Carlos Juan Luis Ana Carmen Pedro Miguel Hans Klaus Jürgen Heike Petra Ursula Stefan Wolfgang Jean Pierre Marie Claire François Nathalie Philippe Isabelle Michel William Elizabeth Linda Susan Karen Richard George Charles Jennifer Patricia Barbara Lisa Nancy Julia Martin Andreas Sabine Elena Lucia Antonio Francisco José Jane Alice Olivia Mohammed Fatima".split())
STREET = frozenset("street st road rd avenue ave lane ln drive dr boulevard blvd court square terrace close way strasse straße weg platz gasse allee rue calle avenida via plaza".split())
STREET_ENDS = ("strasse", "straße", "platz", "gasse", "weg")
MONTHS = frozenset("january february march april may june july august september october november december jan feb mar apr jun jul aug sep sept oct nov dec januar februar märz mai juni juli oktober dezember janvier février mars avril juin juillet août septembre octobre novembre décembre enero febrero marzo abril mayo junio julio agosto septiembre octubre noviembre diciembre".split())
CUES = {
    "secret": "password passwd passwort passphrase pwd secret token api_key apikey api-key access_key key credential contraseña",
    "person": "name mr mrs ms dr prof herr frau madame monsieur señor señora dear sincerely regards patient",
    "birth": "born birth birthday dob geboren geburtsdatum née né naissance nacido nacida nacimiento",
    "iban": "iban account konto compte cuenta",
    "id": "ssn social security passport reisepass passeport pasaporte insurance dni nino id",
    "phone": "tel phone telephone call fax mobile cell telefon téléphone teléfono handy",
    "address": "address adresse dirección lives live living wohnt wohnhaft habite vive resides",
}

_CUE_OF = {w: cue for cue, ws in CUES.items() for w in ws.split()}
_LINKS = frozenset("is was no nr number on at am in le el ist est es the of a my to der den".split())
_WORDS = "|".join(sorted((re.escape(w) for cue in ("secret", "person") for w in CUES[cue].split()), key=len, reverse=True))
_TRIGGER = re.compile(rf"[0-9@]|(?<![^\W_])(?:AKIA|ASIA|AIza)|(?<![^\W_])(?:{'|'.join(sorted(GIVEN))}|(?i:{_WORDS}))(?![^\W\d_])")
_STRONG = re.compile(r"[0-9@]|AKIA|ASIA|AIza")
_TOKEN = re.compile(r"[^\W_]+|[^\w\s]|_")


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        n = ord(d) - 48
        total += (n * 2 - 9 if n > 4 else n * 2) if k % 2 else n
    return total % 10 == 0


def _emails(text: str) -> Iterator[tuple[str, int, int]]:
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL_CHARS:
            start -= 1
        m = _DOMAIN.match(text, at) if start < at else None
        if m:
            yield "email", start, m.end()
            done = m.end()
        at = text.find("@", m.end() if m else at + 1)


def _ips(text: str) -> Iterator[tuple[str, int, int]]:
    """Quadruples of dotted runs; inside one maximal chain the leftmost matches are its consecutive fours."""
    for m in _CHAIN.finditer(text):
        start, parts = m.start(), m.group().split(".")
        for k in range(0, len(parts) - 3, 4):
            end = start + sum(map(len, parts[k : k + 4])) + 3
            if all(len(p.lstrip("0")) <= 3 and int(p[-4:] if len(p) > 4 else p) <= 255 for p in parts[k : k + 4]):
                yield "ip", start, end
            start = end + 1


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end) of the base patterns in code points, by start, then by kind as listed."""
    out = [*_emails(text), *_ips(text)]
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 12:
            digits = m.group().replace(" ", "").replace("-", "")
            if 12 <= len(digits) <= 19 and luhn(digits):
                out.append(("card", m.start(), m.end()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 9 <= sum(c.isdigit() for c in m.group()) <= 15:
                out.append(("phone", m.start(), m.end()))
    return sorted(out, key=lambda s: (s[1], BASE.index(s[0])))


# --- features of whole segments -------------------------------------------------------------------------------------


def shape(s: str) -> str:
    """Digits as 9, letters as a, runs shortened: the outline of a candidate."""
    s = re.sub(r"[^\W\d_]+", "a", s)
    s = re.sub(r"\d+", lambda m: "9" * min(4, len(m.group())), s)
    return re.sub(r"(?:9+a|a9+){3,}[9a]*", "x", s)


def _kind(token: str) -> str:
    """A neighbour's class: a word, a number, a mixture, or the mark itself."""
    return "word" if token.isalpha() else "number" if token.isdigit() else "mixed" if token.isalnum() else token


def _case(token: str) -> str:
    if token.isalpha():
        return "U" if token.isupper() and len(token) > 1 else "T" if token[0].isupper() else "l"
    return "d" if token.isdigit() else "m" if token.isalnum() else token


def cues_before(text: str, tokens: list[tuple[int, int]], i: int) -> tuple[str, str]:
    """The cue among the words before token i, at most four of them with linking words between ("" if there is none), and
    the mark that parts them (a colon, an equals sign or neither)."""
    mark, words, at = "", 0, i - 1
    while at >= 0 and words < 4 and tokens[i][0] - tokens[at][1] < 40:
        word = text[tokens[at][0] : tokens[at][1]].lower()
        if word in ":=":
            mark = mark or word
        elif word.isalpha():
            if (cue := _CUE_OF.get(word)) is not None:
                return cue, mark
            if word not in _LINKS:
                return "", mark
            words += 1
        elif word not in "'\"#.,([_-" or "\n" in text[tokens[at][1] : tokens[i][0]]:
            return "", mark
        at -= 1
    return "", mark


def valid_iban(s: str) -> bool:
    s = s.replace(" ", "")
    return bool(re.fullmatch(r"[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}", s)) and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def _date(s: str) -> bool:
    m = re.fullmatch(r"(\d{1,4})([./-])(\d{1,2})\2(\d{2,4})", s)
    if m:
        a, b, c = int(m[1]), int(m[3]), int(m[4])
        return (len(m[1]) == 4 and 1 <= b <= 12 and 1 <= c <= 31) or (len(m[1]) <= 2 and len(m[4]) in (2, 4) and 1 <= min(a, b) <= 12 and 1 <= max(a, b) <= 31)
    w = re.findall(r"\w+", s)
    return len(w) == 3 and sum(x.lower() in MONTHS for x in w) == 1 and re.fullmatch(r"(1[89]|20)\d\d", w[-1]) is not None


def segment_features(text: str, tokens: list[tuple[int, int]], i: int, j: int, cue: tuple[str, str] | None = None) -> list[str]:
    """Feature names of the segment of tokens i to j - 1."""
    a, b = tokens[i][0], tokens[j - 1][1]
    s = text[a:b]
    digits = [c for c in s if c.isdigit()]
    left = _kind(text[tokens[i - 1][0] : tokens[i - 1][1]]) if i else "^"
    right = _kind(text[tokens[j][0] : tokens[j][1]]) if j < len(tokens) else "$"
    glued_l, glued_r = a > 0 and not text[a - 1].isspace(), b < len(text) and not text[b].isspace()
    parts = [text[x:y] for x, y in tokens[i:j]]
    case = "".join(map(_case, parts[:8]))
    cue, mark = cue if cue is not None else cues_before(text, tokens, i)
    bare = re.sub(r"[^\W\d_]", "a", shape(s)) if len(digits) else "word"
    out = ["bias", f"shape={shape(s)}", f"digits={min(20, len(digits))}", f"tokens={j - i}", f"left={left}", f"right={right}", f"glued={glued_l}{glued_r}", f"letters={any(c.isalpha() for c in s)}", f"case={case}", f"cue={cue}", f"cue={cue}{mark}", f"cue={cue}:{bare}", f"cue={cue}:{case[:3]}", f"ends={_case(parts[0])}{_case(parts[-1])}"]
    if digits and not any(c.isalpha() for c in s):
        runs = re.findall(r"\d+|\D+", s)
        out.append("runs=" + "".join(str(len(r)) if r[0].isdigit() else r for r in runs)[:24])
    if glued_r and right in ("-", "/", ".") and j + 1 <= len(tokens) - 1 and _kind(text[tokens[j + 1][0] : tokens[j + 1][1]]) in ("number", "mixed") and tokens[j + 1][0] == tokens[j][1]:
        out.append("goes_on")
    if glued_l and left in ("-", "/", ".") and i >= 2 and _kind(text[tokens[i - 2][0] : tokens[i - 2][1]]) in ("number", "mixed"):
        out.append("went_on")
    if re.search(r"\s", s):
        out.append("blank")
    if "@" in s:
        out.append("at")
    if s[0] == "+":
        out.append("plus")
    if 12 <= len(digits) <= 19:
        out.append(f"luhn={luhn(''.join(digits))}")
    if re.fullmatch(r"[0-9a-fA-F]{20,64}", s):
        out.append("hexadecimal")
    elif re.fullmatch(r"[\w-]{16,}", s):
        kinds = bool(re.search("[a-z]", s)) + bool(re.search("[A-Z]", s)) + bool(digits)
        out.append(f"long_word={kinds}{len(digits) > 2}")
    if re.match(r"(AKIA|ASIA|ghp_|gho_|sk_|pk_|sk-|xox[abp]-|AIza|glpat-|eyJ)", s):
        out.append("key_prefix")
    if re.fullmatch(r"\d{3}[- ]\d{2}[- ]\d{4}", s):
        out.append("three_two_four")
    if re.fullmatch(r"[A-Z]{1,2}\d{6,9}", s):
        out += ["document_number", f"document_number:{cue}"]
    if s[:2].isupper() and len(digits) > 8 and valid_iban(s):
        out.append("iban_check")
    if len(digits) >= 5 and _date(s):
        out += ["date", f"date:{cue}"]
    words = [p.lower() for p in parts if p.isalpha()]
    if parts[0] in GIVEN:
        out += ["given", f"given:{case[:4]}", f"given:{'T' if right == 'word' and text[tokens[j][0]].isupper() else 'l'}"]
    if words:
        if words[-1] in STREET or words[-1].endswith(STREET_ENDS):
            out += ["street_last", f"street_last:{_case(parts[0])}"]
        if words[0] in STREET:
            out.append("street_first")
        if any(w in STREET or w.endswith(STREET_ENDS) for w in words):
            out += ["street", f"street:{'d' if parts[0].isdigit() else 'D' if parts[-1].isdigit() else 'n'}"]
    return out


def candidates(text: str, tokens: list[tuple[int, int]], cues: list[tuple[str, str]] | None = None) -> Iterator[tuple[int, int]]:
    """Segments that may be personal data: at most MAX_TOKENS tokens, with a trigger inside or a cue before, and single
    blanks only beside marks, between words that begin with capitals, and between these and numbers."""
    cues = cues or [cues_before(text, tokens, i) for i in range(len(tokens))]
    strong = [bool(_STRONG.search(text, a, b)) or text[a:b] in GIVEN for a, b in tokens]
    kind = [_case(text[a:b]) for a, b in tokens]
    word = [k in "TUl" for k in kind]
    low = [text[a:b].lower() for a, b in tokens]
    for i in range(len(tokens)):
        seen = cues[i][0] in ("secret", "person") and kind[i] in "TUlm"
        for j in range(i + 1, min(len(tokens), i + MAX_TOKENS) + 1):
            gap = tokens[j - 1][0] - tokens[j - 2][1] if j - 1 > i else 0
            if gap > 1 or gap and text[tokens[j - 2][1]] == "\n":
                break
            if gap and (word[j - 1] or word[j - 2]):
                x, y = kind[j - 2], kind[j - 1]
                named = y in "TU" and (x in "TUdm.,") or x in "TU" and y in "dm" or low[j - 2] in MONTHS and y == "d" or x in "d." and low[j - 1] in MONTHS or x == "d" and low[j - 1] in STREET or low[j - 2] in STREET and y in "TU" or low[j - 2] in STREET and low[j - 1] in ("de", "la", "des", "du", "del") or low[j - 2] in ("de", "la", "des", "du", "del", "von", "van") and y == "T" and j - 2 > i
                if not named and not (x == "T" and low[j - 1] in ("de", "la", "von", "van", "del") and i < j - 1):
                    break
            seen = seen or strong[j - 1]
            if seen:
                yield i, j


class Taken:
    """Spans as disjoint stretches, looked up by bisection."""

    def __init__(self, spans: list[tuple[str, int, int]]):
        self.starts: list[int] = []
        self.ends: list[int] = []
        for _, a, b in sorted(spans, key=lambda s: s[1]):
            if self.ends and a <= self.ends[-1]:
                self.ends[-1] = max(b, self.ends[-1])
            else:
                self.starts.append(a)
                self.ends.append(b)

    def meets(self, a: int, b: int) -> bool:
        k = bisect_left(self.starts, b) - 1
        return k >= 0 and self.ends[k] > a

    def between(self, a: int, b: int) -> list[tuple[str, int, int]]:
        return [("base", s, e) for s, e in zip(self.starts[bisect_right(self.ends, a) : bisect_left(self.starts, b)], self.ends[bisect_right(self.ends, a) :])]


class Field:
    """Weights and the dynamic programmes of the semi-Markov field."""

    def __init__(self, index: dict[str, int], weights: np.ndarray, moves: np.ndarray):
        self.index, self.weights, self.moves = index, weights, moves

    def segments(self, text: str, tokens: list[tuple[int, int]]) -> list[tuple[int, int, list[int]]]:
        """Candidates with their features, as far as the field knows these."""
        cues = [cues_before(text, tokens, i) for i in range(len(tokens))]
        return [(i, j, [k for k in map(self.index.get, segment_features(text, tokens, i, j, cues[i])) if k is not None]) for i, j in candidates(text, tokens, cues)]

    def best(self, text: str, tokens: list[tuple[int, int]], fixed: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
        """The highest-scoring segmentation that leaves ``fixed`` spans alone; only entities are returned."""
        n, outside = len(tokens), KINDS.index("outside")
        taken = Taken(fixed)
        blocked = [taken.meets(a, b) for a, b in tokens]
        value = np.full((n + 1, len(KINDS)), -np.inf)
        value[0, outside] = 0.0
        back: dict[tuple[int, int], tuple[int, int]] = {}
        by_end: dict[int, list] = {}
        for i, j, f in self.segments(text, tokens):
            if not any(blocked[i:j]):
                by_end.setdefault(j, []).append((i, self.weights[f].sum(axis=0)))
        arrive = np.zeros((n + 1, len(KINDS)))
        came = np.zeros((n + 1, len(KINDS)), dtype=int)
        for j in range(n + 1):
            if j:
                value[j, outside] = arrive[j - 1, outside]
                back[j, outside] = (j - 1, came[j - 1, outside])
                for i, score in by_end.get(j, []):
                    got = arrive[i] + score
                    for k in range(1, len(KINDS)):
                        if got[k] > value[j, k]:
                            value[j, k] = got[k]
                            back[j, k] = (i, came[i, k])
            step = value[j][:, None] + self.moves
            arrive[j], came[j] = step.max(axis=0), step.argmax(axis=0)
        j, k, out = n, int(value[n].argmax()), []
        while j:
            i, before = back[j, k]
            if k != outside:
                out.append((KINDS[k], tokens[i][0], tokens[j - 1][1]))
            j, k = i, int(before)
        return out[::-1]

    def spans(self, text: str, fixed: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
        """Spans of the whole text that the field adds to ``fixed``."""
        out: list[tuple[str, int, int]] = []
        taken = Taken(fixed)
        for a, b in windows(text):
            if any(not taken.meets(m.start(), m.end()) for m in _TRIGGER.finditer(text, a, b)):
                out += self.best(text, [(m.start(), m.end()) for m in _TOKEN.finditer(text, a, b)], taken.between(a, b))
        return out


def windows(text: str) -> Iterator[tuple[int, int]]:
    """Stretches of tokens that touch a trigger or a cue: those fewer than 80 characters apart share one."""
    start = end = None
    for m in _TRIGGER.finditer(text):
        if end is not None and m.start() - end > 80:
            yield _widen(text, start, end)
            start = None
        start = m.start() if start is None else start
        end = m.end()
    if end is not None:
        yield _widen(text, start, end)


def _widen(text: str, a: int, b: int) -> tuple[int, int]:
    """40 characters on, and on to the end of the word."""
    a, b = max(0, a - 40), min(len(text), b + 40)
    while a > 0 and text[a - 1].isalnum():
        a -= 1
    while b < len(text) and text[b].isalnum():
        b += 1
    return a, b


# --- training -------------------------------------------------------------------------------------------------------


def _made_entity(r: random.Random) -> tuple[str, str, str]:
    """(text before, entity, kind) of one generated entity or, under "outside", of a look-alike."""
    d = lambda n: "".join(r.choice("0123456789") for _ in range(n))
    w = lambda: "".join(r.choice(("an", "er", "lo", "mi", "tu", "sh", "ve", "ra", "ber", "kin", "wal", "to")) for _ in range(r.randint(1, 3)))
    cap = lambda: w().capitalize()
    some = lambda chars, n: "".join(r.choice(chars) for _ in range(n))
    cue = lambda kind: r.choice(CUES[kind].split())
    upper, letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ"
    hexed = some("0123456789abcdef", r.choice((32, 40, 24, 64)))
    given, sep = r.choice(sorted(GIVEN)), r.choice((": ", " ", " is ", ": "))
    day, month, year = r.randint(1, 28), r.randint(1, 12), r.randint(1925, 2012)
    date = r.choice((f"{day:02d}/{month:02d}/{year}", f"{month:02d}/{day:02d}/{year}", f"{year}-{month:02d}-{day:02d}", f"{day}.{month}.{year}", f"{day} {r.choice(sorted(MONTHS)).capitalize()} {year}"))
    phone = r.choice((f"({d(3)}) {d(3)}-{d(4)}", f"{d(3)}-{d(3)}-{d(4)}", f"{d(3)}.{d(3)}.{d(4)}", f"0{d(2)} {d(4)} {d(4)}", f"0{d(3)} {d(6)}", f"0{d(1)} {d(2)} {d(2)} {d(2)} {d(2)}", f"{d(3)}-{d(4)}", f"0{d(3)}/{d(7)}"))
    card = d(r.choice((12, 14, 15, 15, 15, 15)))
    card += next(c for c in "0123456789" if luhn(card + c))
    pick = r.randint(0, 33)
    if pick == 0:
        return "", f"{w()}.{w()}{d(2)}@{w()}.{r.choice(('com', 'org', 'net'))}", "email"
    if pick == 1:
        return "", ".".join(str(r.randint(0, 255)) for _ in range(4)), "ip"
    if pick == 2:
        return "", card, "card"
    if pick == 3:
        return "", f"+{r.randint(1, 99)} ({d(3)}) {d(3)}-{d(4)}", "phone"
    if pick in (4, 5):
        return r.choice(("", "", cue("phone") + r.choice((" ", ": ", ". ")))), phone, "phone"
    if pick == 6:
        return cue("phone") + r.choice((" ", ": ", " is ", " on ")), phone, "phone"
    if pick in (7, 8):
        q = r.choice(('"', "'", ""))
        key = r.choice((hexed, some(letters + "0123456789", r.choice((16, 20, 32, 40))), f"ghp_{some(letters + '0123456789', 36)}", f"sk_live_{some(letters + '0123456789', 24)}"))
        return cue("secret") + r.choice((" = ", "=", ": ")) + q, key, "secret"
    if pick in (9, 10):
        q = r.choice(('"', "'", "", "", ""))
        return r.choice(("password", "Password", "passwd", "pwd", "Passwort", "passphrase", "secret")) + r.choice((": ", "=", " = ", ":")) + q, r.choice((w() + w(), w() + d(3), cap() + d(2) + "!", w() + "-" + w(), some(letters + "0123456789", 10))), "secret"
    if pick == 11:
        return "", r.choice((hexed, f"AKIA{some(upper + '0123456789', 16)}", f"ghp_{some(letters + '0123456789', 36)}", f"AKIA{some(upper, 12)}{w().upper()}", f"AIza{some(letters + '0123456789', 35)}")), "secret"
    if pick == 12:
        return r.choice(("", "id ", "number ")), f"{d(3)}-{d(2)}-{d(4)}", "national_id"
    if pick == 13:
        return cue("id") + r.choice((": ", " ", " is ", " no. ", " number ")), r.choice((f"{d(3)} {d(2)} {d(4)}", f"{some(upper, 2)}{d(7)}", f"{some(upper, 1)}{d(8)}", f"{d(3)}-{d(2)}-{d(4)}", f"{d(9)}", f"{some(upper, 2)} {d(2)} {d(2)} {d(2)} {some('ABCD', 1)}")), "national_id"
    if pick == 14:
        return "", r.choice((f"{some(upper, 2)}{d(7)}", f"{some(upper, 2)}{d(6)}{some('ABCD', 1)}")), "national_id"
    if pick in (15, 16):
        country, body = r.choice((("DE", d(18)), ("FR", d(23)), ("ES", d(20)), ("GB", some(upper, 4) + d(14)), ("AT", d(16))))
        check = 98 - int("".join(str(int(c, 36)) for c in body + country + "00")) % 97
        iban = f"{country}{check:02d}{body}"
        return r.choice(("", "IBAN ", "IBAN: ", "account ")), " ".join(iban[k : k + 4] for k in range(0, len(iban), 4)) if r.random() < 0.6 else iban, "iban"
    if pick in (17, 18):
        return r.choice(("", "", "Dear ", "name: ", "by ", "with ")), given + " " + r.choice((cap(), cap(), f"{some(upper, 1)}. {cap()}", f"{cap()}-{cap()}")), "person"
    if pick in (19, 20):
        return r.choice(("Mr", "Mrs", "Ms", "Dr", "Mr.", "Dr.", "Herr", "Frau", "my name is", "Name:", "Dear", "patient")) + " ", r.choice((cap(), f"{cap()} {cap()}", f"{given} {cap()}", cap())), "person"
    if pick in (21, 22):
        name = cap() + r.choice(("", f" {cap()}"))
        return r.choice(("", "", cue("address") + " at ", "address: ", "at ")), r.choice((f"{r.randint(1, 400)} {name} {r.choice(('Street', 'Road', 'Avenue', 'Lane', 'St', 'Rd', 'Drive', 'Square'))}", f"{cap()}straße {r.randint(1, 200)}", f"{cap()}strasse {r.randint(1, 200)}", f"{r.randint(1, 99)} rue de {cap()}", f"{r.randint(1, 99)} rue {cap()}", f"Calle {cap()} {r.randint(1, 99)}", f"{cap()}weg {r.randint(1, 90)}" if r.random() < 0.2 else f"{r.randint(1, 400)} {name} Street")), "address"
    if pick in (23, 24):
        return cue("birth") + r.choice((" ", ": ", " on ", " is ", " am ", " le ")), date, "birth_date"
    n = d(3)
    other = (
        f"version {r.randint(1, 9)}.{r.randint(0, 20)}", f"{r.randint(1900, 2030)}", f"{d(1)},{d(3)}.{d(2)}", date, f"on {date}", f"{d(2)}:{d(2)}", f"{d(16)}", f"{d(16)}", f"{d(2)} %", f"page {d(3)}", f"{d(9)}{w()}",
        f"{d(3)}.{d(3)}", f"{w()}@", f"{d(6)}", f"{d(8)}", f"{d(10)}", f"3{d(2)}.{d(3)}.4{d(2)}.9{d(2)}", f"{d(5)}/{d(4)}", f"no. {d(2)}", f"{d(5)} {d(4)} {d(3)}",
        f"{cap()} {cap()}", f"{cap()} {cap()}", f"{cap()} {r.randint(1, 99)}", f"{r.randint(2, 99)} {cap()} {cap()}", f"{given} {w()}", f"{given}, {w()}", f"{d(3)}-{d(3)}-{d(4)}-{d(2)}", f"{n}-{d(4)}-{d(3)}-{d(5)}", f"Order {d(3)}-{d(3)}-{d(4)}-{d(2)}",
        f"{cue('secret')} {w()} {w()}", f"{cue('secret')} {w()}", f"the {cue('secret')} of {w()}", f"{cue('person')} of {w()}", f"{w()} {cue('id')} {w()}", f"{w()}-{d(2)}", f"{some(upper, 1)}{d(2)}", f"{some(upper, 3)}-{d(4)}", f"License, version {d(1)}.", f"License, Version {d(1)}.{d(1)}.", f"{cue('id')}, Version {d(1)}.{d(1)}", f"{cue('id')} section {d(1)}.{d(2)}", f"{cap()} {d(1)}.{d(1)}", f"CC BY-NC {d(1)}.{d(1)}", f"born in {r.randint(1900, 2010)}", f"{d(2)} street", f"in the street {w()}", f"{d(4)}-{d(4)}", f"{d(1)}-{d(1)}", f"chapter {d(1)}.{d(1)}.{d(1)}",
    )
    return "", r.choice(other), "outside"


def made_sentences(n: int, seed: int = 11) -> list[tuple[str, list[tuple[str, int, int]]]]:
    """Seeded training sentences with the spans to be found."""
    r, out = random.Random(seed), []
    words = "the of von que les tion Er anon ist para ou Stre with und and we sent it please note that today She The Die les une para esta in on for from was has been Sie wir nicht avec pour dans los del con por haed, ist. are&&& *** und!!".split()
    for _ in range(n):
        text, spans = " ".join(r.choices(words, k=r.randint(1, 4))) + " ", []
        for _ in range(r.randint(1, 2)):
            before, entity, kind = _made_entity(r)
            text += before
            if kind != "outside":
                spans.append((kind, len(text), len(text) + len(entity)))
            quote = before[-1:] if before[-1:] in ("'", '"') else ""
            text += entity + quote + r.choice((" ", " ", ", ", ". ", ".\n", "### ", "!! ")) + " ".join(r.choices(words, k=r.randint(2, 4))).lower() + " "
        out.append((text, spans))
    return out


def _sums(weights: np.ndarray, segs: list[tuple[int, int, list[int]]]) -> np.ndarray:
    """The score of every segment by kind; "outside" is none of theirs."""
    if not segs:
        return np.zeros((0, len(KINDS)))
    out = np.add.reduceat(weights[np.concatenate([f for _, _, f in segs])], np.cumsum([0] + [len(f) for _, _, f in segs[:-1]]))
    out[:, 0] = -np.inf
    return out


def _expected(n: int, segs: list, score: np.ndarray, moves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Probabilities of the segments by kind, and expected numbers of moves, by forward and backward sums."""
    k = len(KINDS)
    ends: dict[int, list[int]] = {}
    starts: dict[int, list[int]] = {}
    for q, (i, j, _) in enumerate(segs):
        ends.setdefault(j, []).append(q)
        starts.setdefault(i, []).append(q)
    first, last = np.array([i for i, _, _ in segs], int), np.array([j for _, j, _ in segs], int)
    alpha, into = np.full((n + 1, k), -np.inf), np.zeros((n + 1, k))
    alpha[0, 0] = 0
    for j in range(n + 1):
        if j:
            alpha[j, 0] = into[j - 1, 0]
            if j in ends:
                q = ends[j]
                alpha[j] = np.logaddexp(alpha[j], np.logaddexp.reduce(into[first[q]] + score[q], axis=0))
        into[j] = np.logaddexp.reduce(alpha[j][:, None] + moves, axis=0)
    beta, onward = np.full((n + 1, k), -np.inf), np.full((n + 1, k), -np.inf)  # onward: of entering a segment of a kind
    beta[n] = 0
    for i in range(n - 1, -1, -1):
        onward[i, 0] = beta[i + 1, 0]
        if i in starts:
            q = starts[i]
            onward[i] = np.logaddexp(onward[i], np.logaddexp.reduce(beta[last[q]] + score[q], axis=0))
        beta[i] = np.logaddexp.reduce(moves + onward[i][None, :], axis=1)
    z = np.logaddexp.reduce(alpha[n])
    chance = np.exp(np.minimum(into[first] + score + beta[last] - z, 0)) if segs else np.zeros((0, k))
    moved = np.exp(np.minimum(alpha[:n, :, None] + moves[None] + onward[:n, None, :] - z, 0)).sum(axis=0)
    return chance, moved


def train(sentences: int = 1500, epochs: int = 5, rate: float = 0.25, shrink: float = 1e-4, seed: int = 11) -> Field:
    """Maximum likelihood by stochastic gradient on expected segment features."""
    grow: dict[str, int] = {}
    field = Field(grow, np.zeros((0, len(KINDS))), np.zeros((len(KINDS),) * 2))
    ready = []
    for text, spans in made_sentences(sentences, seed):
        tokens = [(m.start(), m.end()) for m in _TOKEN.finditer(text)]
        cues = [cues_before(text, tokens, i) for i in range(len(tokens))]
        segs = [(i, j, [grow.setdefault(f, len(grow)) for f in segment_features(text, tokens, i, j, cues[i])]) for i, j in candidates(text, tokens, cues)]
        starts, ends = {a: k for k, (a, _) in enumerate(tokens)}, {b: k + 1 for k, (_, b) in enumerate(tokens)}
        gold = {(starts[a], ends[b]): KINDS.index(kind) for kind, a, b in spans if a in starts and b in ends}
        able = {(i, j) for i, j, _ in segs}
        gold = {at: y for at, y in gold.items() if at in able}
        ready.append((len(tokens), segs, gold))
    field.weights = np.zeros((len(grow), len(KINDS)))
    field.weights[grow["bias"], 1:] = -1.0
    r, k = random.Random(seed), len(KINDS)
    for epoch in range(epochs):
        r.shuffle(ready)
        step = rate / (1 + 0.4 * epoch)
        for n, segs, gold in ready:
            chance, moved = _expected(n, segs, _sums(field.weights, segs), field.moves)
            g = -chance
            g[:, 0] = 0
            for q, (i, j, _) in enumerate(segs):
                if (i, j) in gold:
                    g[q, gold[i, j]] += 1
            some = np.flatnonzero(np.abs(g).max(axis=1, initial=0) > 1e-4) if len(g) else []
            if len(some):
                np.add.at(field.weights, np.concatenate([segs[q][2] for q in some]), step * np.repeat(g[some], [len(segs[q][2]) for q in some], axis=0))
            true, at, last = np.zeros((k, k)), 0, 0
            by_start = {i: (j, y) for (i, j), y in gold.items()}
            while at < n:
                nxt, y = by_start.get(at, (at + 1, 0))
                true[last, y] += 1
                at, last = nxt, y
            field.moves += 0.1 * step * (true - moved)
            field.moves -= field.moves[0, 0]
        field.weights *= 1 - shrink
    return field


@lru_cache(maxsize=1)
def trained() -> Field:
    return train()


# --- Spark ----------------------------------------------------------------------------------------------------------


def find(text: str | None, field: Field) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
    """(base spans, all spans) of a whole text; null counts as empty.  All spans are by start, then kind."""
    text = text or ""
    base = base_spans(text)
    extra = field.spans(text, base)
    return base, sorted([*base, *extra], key=lambda s: (s[1], KINDS.index(s[0])))


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def redacted(text: str | None, spans: list[tuple[str, int, int]]) -> str | None:
    """The text with every maximal run of overlapping spans replaced by the kind of its first one."""
    if not text or not spans:
        return text
    out, at = [], 0
    for kind, a, b in spans:
        if a >= at:
            out += [text[at:a], f"<{kind}>"]
        at = max(at, b)
    return "".join(out) + text[at:]


def _apply(docs: DataFrame, schema: str, row, field: Field | None, out: str) -> DataFrame:

    sent = docs.sparkSession.sparkContext.broadcast(field or trained())
    names = [c.split()[0] for c in schema.split(",")]

    @F.pandas_udf(schema)
    def found(texts: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([row(t if isinstance(t, str) else None, sent.value) for t in texts], columns=names)

    return docs.withColumn(out, found("text"))


def _digest(text: str | None, field: Field) -> tuple:
    base, spans = find(text, field)
    n = [sum(k == kind for k, _, _ in base) for kind in BASE]
    return (*n, hashlib.sha256(joined(base).encode()).hexdigest(), joined(spans))


def detect(docs: DataFrame, field: Field | None = None) -> DataFrame:
    """doc_id and the personal data of every whole text: counts and hash of the base spans, and all spans.

    Null text counts as empty.  A row for each row, repeated ones too; other columns are not read.  Empty table: empty result.
    """
    out = _apply(docs.select("doc_id", "text"), "n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string", _digest, field, "_found")
    return out.select("doc_id", "_found.*")


def redact(docs: DataFrame, field: Field | None = None) -> DataFrame:
    """``docs`` with personal data in ``text`` replaced and n_chars, if there, of the new text; all rows and columns stay.

    Null texts and texts without personal data are as they were.
    """
    out = fresh(docs, "_clean")
    done = _apply(docs, "t string", lambda t, f: (redacted(t, find(t, f)[1]),), field, out).withColumn("text", F.col(f"{out}.t")).drop(out)
    return done.withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars"))) if "n_chars" in docs.columns else done
