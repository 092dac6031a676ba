"""PII surrogates: detected entities get keyed, type-consistent replacements.

* A mention is reduced to a canonical form (digits of a phone number, lower-cased
  address, case-folded name), so that mentions of one entity get one surrogate.
* A surrogate is drawn from HMAC-SHA256 of the key, kind, canonical form and an attempt
  number, and keeps what the kind and the format say: lengths, punctuation and letter
  case; a phone's country prefix; a card's first digit and check digit; a private
  network's prefix; an IBAN's country and check digits; a domain's surrogate is that of
  the domain, so addresses of one domain stay together; a name keeps its title's gender
  and its script.
* A name is detected behind a title, behind words that introduce a person ("my name is",
  "signed"), where a common given name comes before a capitalised word, and where two
  capitalised words spell the local part of an address in the text.  In the same text every
  other mention of that full name, given name or family name gets the matching part of its
  surrogate, and a title with a family name alone means the full name before it (or else the
  first one).
* Collision checks run over the distinct entities of all documents: two entities never
  share a surrogate, nor do two mail domains, and no surrogate is itself an entity of the
  corpus.  Losers draw again with the next attempt.  Only entities with an attempt above 0
  need a table.
* A private network's addresses have few surrogates.  Where the corpus holds over a quarter
  of such a network, its surrogates are a keyed permutation of the network: still
  distinct, but each may be another address of the corpus.
* The key is the caller's; there is no default.

Defined cases: null texts stay null; texts without entities stay as they are; repeated
rows are rewritten alike; very long texts are scanned whole; other columns pass through
``rewrite``; an empty table gives an empty result.
"""

from __future__ import annotations

import bisect
import functools
import hashlib
import hmac
import itertools
import re
import unicodedata
from collections.abc import Iterator
from dataclasses import dataclass

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import Store

KINDS = ("email", "phone", "ip", "card", "ssn", "iban", "name")
#: Entities with an attempt above 0 that may be broadcast; attempts before a longer form is drawn, and at most.
SMALL, ROUNDS, MOST = 50_000, 12, 200

#: Titles and the gender they show (n: none).
TITLES = {"Mr": "m", "Mrs": "f", "Ms": "f", "Herr": "m", "Frau": "f", "Monsieur": "m", "Madame": "f", "Señor": "m", "Señora": "f", "Господин": "m", "Госпожа": "f", "Κύριος": "m", "Κυρία": "f"}
TITLES |= {"Miss": "f", "Mme": "f", "Mlle": "f", "Mademoiselle": "f", "Sir": "m", "Sr": "m", "Sra": "f", "Srta": "f", "Señorita": "f", "Signor": "m", "Signora": "f"}
TITLES |= dict.fromkeys(["Dr", "Dra", "Dott", "Prof", "Professor", "Доктор", "Профессор"], "n")
#: Given names by script and gender.
GIVEN = {
    ("LATIN", "m"): "Adam Bruno Carl David Emil Felix Hugo Jonas Leon Martin Oscar Paul".split(),
    ("LATIN", "f"): "Alma Berta Clara Diana Emma Flora Greta Helena Irma Laura Marta Nora".split(),
    ("CYRILLIC", "m"): "Антон Борис Виктор Григорий Денис Иван Максим Павел".split(),
    ("CYRILLIC", "f"): "Анна Вера Дарья Елена Ирина Мария Ольга Юлия".split(),
    ("GREEK", "m"): "Ανδρέας Γιώργος Δημήτρης Νίκος Πέτρος Σπύρος".split(),
    ("GREEK", "f"): "Άννα Ελένη Ζωή Κατερίνα Μαρία Σοφία".split(),
}
#: Syllables of family names by script.
SYLLABLES = {"LATIN": "ba del fin gor hal kem lin mar nor pel ros sel tan vor wen zim".split(), "CYRILLIC": "ба вел дан кор лин мар нов пет сол тар".split(), "GREEK": "βα δελ καν λιν μαρ νικ πετ σολ ταρ".split()}

_EMAIL = r"(?P<email>[A-Za-z0-9._%+\-]+@[A-Za-z0-9\-]+(?:\.[A-Za-z0-9\-]+)*\.[A-Za-z]{2,})"
_IBAN = r"(?P<iban>\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b)"
_IP = r"(?P<ip>(?<![\w.])(?:\d{1,3}\.){3}\d{1,3}(?![\w]|\.\d))"
_SSN = r"(?P<ssn>(?<![\w\-])\d{3}-\d{2}-\d{4}(?![\w\-]))"
_CARD = r"(?P<card>(?<![\w\-])(?:\d{13,19}|\d{4}(?:[ \-]\d{4}){3}|\d{4}[ \-]\d{6}[ \-]\d{5})(?![\w\-]))"
_PHONE = r"(?P<phone>(?<![\w+])(?:\+\d{1,3}[ .\-]?(?:\(\d{1,4}\)[ .\-]?)?\d{2,4}(?:[ .\-]?\d{2,4}){1,4}|\(\d{3}\)[ .\-]?\d{3}[ .\-]\d{4}|\d{3}[.\-]\d{3}[.\-]\d{4})(?![\w]))"
_DIGITS = re.compile("|".join((_IP, _SSN, _CARD, _PHONE, _IBAN)))
_AT = re.compile(_EMAIL)
_TITLE = r"(?:" + "|".join(TITLES) + r")\b\.? "
#: Words that introduce a person (both names must follow).
INTRODUCTIONS = ["[Mm]y name is", "I am called", "[Ss]igned,?", "[Ss]igned by", "[Yy]ours sincerely,", "[Ss]incerely,", "[Rr]egards,", "[Mm]ein Name ist", "[Ii]ch heiße", "[Gg]ezeichnet,?", "Mit freundlichen Grüßen,?", "[Jj]e m['’]appelle", "[Mm]on nom est", "[Ss]igné,?", "[Mm]e llamo", "[Mm]i nombre es", "[Ff]irmado,?", "Atentamente,", "[Cc]ontact(?: person)?:", "[Aa]uthor:", "Attn:", "Ansprechpartner(?:in)?:"]
#: Common given names that reveal a person before a capitalised word.
COMMON = {"m": "James John Robert Michael William David Richard Thomas Charles Daniel Matthew Andrew Peter Hans Jürgen Klaus Wolfgang Stefan Andreas Matthias Pierre Jean Michel François Jacques Philippe Nicolas Carlos José Juan Luis Miguel Pedro Javier Antonio Manuel Diego Pablo".split(), "f": "Mary Patricia Jennifer Linda Elizabeth Susan Jessica Sarah Karen Emily Anna Anne Ursula Petra Sabine Monika Katrin Claudia Heike Marie Isabelle Sophie Nathalie Catherine Françoise Camille María Carmen Ana Isabel Lucía Elena Teresa Rosa Cristina".split()}
_NAMED = {n: g for g, own in COMMON.items() for n in own}
_WORD = r"[^\W\d_a-zà-ÿ][^\W\d_]+(?:-[^\W\d_a-zà-ÿ][^\W\d_]+)?"
_INTRODUCED = re.compile(r"(?:\b(?:" + "|".join(INTRODUCTIONS) + r")\s+(?P<name>" + _WORD + " " + _WORD + r")|\b(?P<given>(?:" + "|".join(_NAMED) + r") " + _WORD + r"))(?!\w)")
_TITLED = re.compile(r"\b(?P<titles>(?:" + _TITLE + r")+)(?P<name>[^\W\d_][\w'’\-]*(?: [^\W\d_][\w'’\-]*)?)")
_NAME = re.compile(r"[^\W\d_][\w'’\-]*")
_HAS_DIGIT = re.compile(r"\d{2}")

_RUN = re.compile(r"[^\W_]+")
#: Digits of a national number by country prefix, and lengths of IBANs by country.
NATIONAL = {"1": (10,), "7": (10,), "30": (10,), "31": (9,), "32": (8, 9), "33": (9,), "34": (9,), "41": (9,), "44": (9, 10), "45": (8,), "47": (8,), "48": (9,), "52": (10,), "55": (10, 11), "61": (9,), "81": (9, 10), "86": (10, 11), "91": (10,), "351": (9,), "353": (7, 8, 9), "420": (9,)}
IBANS = dict(x.split(":") for x in "AD:24 AE:23 AL:28 AT:20 AZ:28 BA:20 BE:16 BG:22 BH:22 BR:29 BY:28 CH:21 CR:22 CY:28 CZ:24 DE:22 DK:18 DO:28 EE:20 EG:29 ES:24 FI:18 FO:18 FR:27 GB:22 GE:22 GI:23 GL:18 GR:27 GT:28 HR:21 HU:28 IE:22 IL:23 IQ:23 IS:26 IT:27 JO:30 KW:30 KZ:20 LB:28 LC:32 LI:21 LT:20 LU:20 LV:21 MC:27 MD:24 ME:22 MK:19 MR:27 MT:31 MU:30 NL:18 NO:15 PK:24 PL:28 PS:29 PT:25 QA:29 RO:24 RS:22 SA:24 SC:31 SE:24 SI:19 SK:24 SM:27 ST:25 SV:28 TL:23 TN:24 TR:26 UA:29 VA:22 VG:24 XK:20".split())


@functools.cache
def _cues() -> ahocorasick.Automaton:
    """Finds texts that may name a person: titles, given names, and the longest word of each introduction."""
    plain = (re.sub(r"\[[^\]]*\]|\(\?:[^)]*\)\?", " ", x) for x in INTRODUCTIONS)
    found = ahocorasick.Automaton()
    for word in {*TITLES, *_NAMED, *(max(re.findall(r"[^\W\d_]+", x), key=len) for x in plain)}:
        found.add_word(word, True)
    found.make_automaton()
    return found


@dataclass(frozen=True)
class Mention:
    start: int
    end: int
    kind: str
    canon: str


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (2 if k % 2 else 1)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def _mod97(iban: str) -> int:
    return int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97


def script(text: str) -> str:
    for c in text:
        if c.isalpha():
            found = unicodedata.name(c, "").split(" ")[0]
            return found if found in SYLLABLES else "LATIN"
    return "LATIN"


def _valid(kind: str, value: str) -> int:
    """Length of the valid entity that a match begins with (0: none); ends are ends of digit or letter runs."""
    digits = re.sub(r"\D", "", value)
    if kind == "ip":
        return len(value) if max(map(int, value.split("."))) <= 255 else 0
    if kind == "card":
        return len(value) if luhn(digits) or len(digits) == 16 else 0
    ends = [m.end() for m in _RUN.finditer(value)][::-1]
    if kind == "phone":
        counts = {e: sum(map(str.isdigit, value[:e])) for e in ends}
        if value[0] == "+":
            for k in (1, 2, 3):
                wanted = [k + n for n in NATIONAL.get(digits[:k], ())]
                if fits := [e for e in ends if counts[e] in wanted]:
                    return fits[0]
        return next((e for e in ends if 7 <= counts[e] <= 15), 0)
    if kind == "iban":
        exact = int(IBANS.get(value[:2], 0))
        fits = [e for e in ends if len(value[:e].replace(" ", "")) == exact] if exact else ends
        return next((e for e in (*fits, len(value)) if e > 4 and _mod97(value[:e].replace(" ", "")) == 1), 0)
    return len(value)


def _bare(word: str) -> str:
    """A name without its possessive ending."""
    return word[:-2] if len(word) > 2 and word[-2:] in ("'s", "’s") else word


def _spelled(text: str) -> Iterator[tuple[int, str]]:
    """Pairs of capitalised words that an address in the text spells (given.family or the like)."""
    locals_ = {tuple(w for w in re.split(r"[._\-]", m[0].split("@")[0].lower()) if w) for m in _AT.finditer(text)}
    pairs = {p for p in locals_ if len(p) == 2 and min(map(len, p)) > 1 and "".join(p).isalpha()}
    words = list(_NAME.finditer(text)) if pairs else []
    for a, b in itertools.pairwise(words):
        if text[a.end() : b.start()] == " " and (a[0].casefold(), _bare(b[0]).casefold()) in pairs and a[0][0].isupper() and b[0][0].isupper():
            yield a.start(), f"{a[0]} {_bare(b[0])}"


def _names(text: str, cued: bool) -> list[Mention]:
    """Names that titles, introductions, common given names or addresses reveal, and all other
    mentions of these persons or of a part of their names.  ``cued``: the text may hold more than
    addresses."""
    titled = []
    for m in _TITLED.finditer(text) if cued else ():
        words = m["name"].split(" ")
        if not words[0][0].isupper():
            continue
        name = _bare(words[0] if len(words) == 1 or not words[1][0].isupper() else m["name"])
        gender = next((g for t in _NAME.findall(m["titles"]) if (g := TITLES[t]) != "n"), "n")
        titled.append((m.start("name"), m.start("name") + len(name), gender, name.casefold()))
    known = {at for at, *_ in titled}
    others = [(m.start(k), _bare(m[k])) for m in (_INTRODUCED.finditer(text) if cued else ()) for k in ("name", "given") if m[k]] + list(_spelled(text) if "@" in text else ())
    for at, name in others:
        if at not in known and len(name.split(" ")) == 2:
            known.add(at)
            titled.append((at, at + len(name), _NAMED.get(name.split(" ")[0], "n"), name.casefold()))
    titled.sort()
    shown = {}  # the first gender that a full name's titles show
    for _, _, gender, name in titled:
        if gender != "n" or name not in shown:
            shown[name] = gender if shown.get(name, "n") == "n" else shown[name]
    full = [(at, f"{shown[name] if gender == 'n' else gender}:{name}") for at, _, gender, name in titled if " " in name]

    def fitting(gender: str, canon: str) -> bool:
        return "n" in (gender, canon[0]) or gender == canon[0]

    def person(at: int, among: list[tuple[int, str]]) -> str | None:
        """The last one before a place, or else the first one."""
        k = bisect.bisect_right(among, at, key=lambda x: x[0])
        return among[max(0, k - 1)][1] if among else None

    families: dict[str, list[tuple[int, str]]] = {}
    parts: dict[str, list[tuple[int, str]]] = {}
    for at, canon in full:
        given, family = canon[2:].split(" ")
        families.setdefault(family, []).append((at, canon))
        for part in (given, family, canon[2:]):
            parts.setdefault(part, []).append((at, canon))
    found, named = [], []
    for at, end, gender, name in titled:
        if " " in name:
            canon = f"{shown[name] if gender == 'n' else gender}:{name}"
        else:
            same = [x for x in families.get(name, ()) if fitting(gender, x[1])] if name in families else []
            canon = person(at, same) or f"{shown[name] if gender == 'n' else gender}:{name}"
            named.append((at, name, canon))
        found.append(Mention(at, end, "name", canon))
    for at, name, canon in named:
        parts.setdefault(name, []).append((at, canon))
    for own in parts.values():
        own.sort()
    starts, last = {m.start for m in found}, None
    for m in _NAME.finditer(text) if parts else ():
        word = _bare(m[0])
        if last and text[last.end() : m.start()] == " " and (both := f"{last[0]} {word}".casefold()) in parts and last[0][0].isupper() and last.start() not in starts:
            found.append(Mention(last.start(), m.start() + len(word), "name", person(m.start(), parts[both])))
        if len(word) > 1 and word[0].isupper() and m.start() not in starts and (word.casefold() in parts):
            found.append(Mention(m.start(), m.start() + len(word), "name", person(m.start(), parts[word.casefold()])))
        last = m
    return found


def mentions(text: str) -> list[Mention]:
    """Entities of a text, by start, not overlapping."""
    found: list[Mention] = []
    if "@" in text:
        found += [Mention(m.start(), m.end(), "email", m[0].lower()) for m in _AT.finditer(text)]
    if _HAS_DIGIT.search(text):
        at = 0
        while m := _DIGITS.search(text, at):
            kind = m.lastgroup
            end = m.start() + _valid(kind, m[0])
            if end == m.start():  # go on behind the first token
                at = _RUN.search(text, end).end()
                continue
            value, at = text[m.start() : end], end
            canon = value if kind == "ip" else value.replace(" ", "") if kind == "iban" else re.sub(r"\D", "", value)
            found.append(Mention(m.start(), end, kind, canon))
    cued = next(_cues().iter(text), None) is not None
    if cued or any(m.kind == "email" for m in found):
        found += _names(text, cued)
    out: list[Mention] = []
    for m in sorted(found, key=lambda m: (m.start, -m.end)):
        if not out or m.start >= out[-1].end:
            out.append(m)
    return out


class _Draw:
    """A stream of keyed choices."""

    def __init__(self, key: bytes, *what: object) -> None:
        self.key, self.what, self.turn, self.left = key, "\x1f".join(map(str, what)).encode(), 0, b""

    def below(self, n: int) -> int:
        if len(self.left) < 4:
            self.left += hmac.new(self.key, self.what + b"\x1e%d" % self.turn, hashlib.sha256).digest()
            self.turn += 1
        value, self.left = int.from_bytes(self.left[:4], "big"), self.left[4:]
        return value * n >> 32

    def like(self, text: str) -> str:
        """Letters for letters and digits for digits."""
        return "".join(chr(97 + self.below(26)) if c.isalpha() else str(self.below(10)) if c.isdigit() else c for c in text)


def network(canon: str) -> tuple[int, int]:
    """First address and size of the private network of an address (size 0: public)."""
    a, b, *_ = map(int, canon.split("."))
    if a in (10, 127):
        return a << 24, 1 << 24
    if (a, b) == (192, 168):
        return 192 << 24 | 168 << 16, 1 << 16
    return (172 << 24 | 16 << 16, 1 << 20) if a == 172 and 16 <= b < 32 else (0, 0)


def _dotted(value: int) -> str:
    return ".".join(str(value >> k & 255) for k in (24, 16, 8, 0))


def permuted(canon: str, key: bytes) -> str:
    """A keyed permutation of a private network without fixed points.

    A Feistel network of four rounds puts the addresses on a ring, and each gets the next one.
    """
    first, size = network(canon)
    half = (size.bit_length() - 1) // 2
    mask = (1 << half) - 1
    mixed = lambda turn, x: _Draw(key, "network", first, turn, x).below(1 << half)
    value = sum(int(x) << k for x, k in zip(canon.split("."), (24, 16, 8, 0), strict=True)) - first
    left, right = value >> half, value & mask
    for turn in range(4):
        left, right = right, left ^ mixed(turn, right)
    value = ((left << half | right) + 1) % size
    left, right = value >> half, value & mask
    for turn in reversed(range(4)):
        left, right = right ^ mixed(turn, left), left
    return _dotted(first + (left << half | right))


def surrogate(kind: str, canon: str, attempt: int, key: bytes, domain: int = 0, full: frozenset[int] = frozenset()) -> str:
    """The canonical surrogate of a canonical entity.

    ``domain``: the attempt of an address's domain; ``full``: first addresses of the networks
    whose surrogates are permuted.
    """
    draw = _Draw(key, kind, canon, attempt)
    longer = "0" * max(0, attempt - ROUNDS)  # a crowded format: give up its length before distinctness
    if kind == "domain":
        *labels, top = canon.split(".")
        return f"{draw.like('.'.join(labels) + longer)}.{top}"
    if kind == "email":
        local, place = canon.rsplit("@", 1)
        return f"{draw.like(local + longer)}@{surrogate('domain', place, domain, key)}"
    if kind == "ip":
        first, size = network(canon)
        if first in full:
            return permuted(canon, key)
        if size:
            return _dotted(first + draw.below(size))
        return ".".join(map(str, [12 + draw.below(110), *(draw.below(256) for _ in range(3))]))
    if kind == "card":
        body = canon[0] + draw.like(canon[1:-1] + longer)
        return next(body + d for d in "0123456789" if luhn(body + d)) if luhn(canon) else body + draw.like("0")
    if kind == "phone":
        kept = 1 if len(canon) in (11, 12, 13) else 0
        return canon[:kept] + str(2 + draw.below(8)) + draw.like(canon[kept + 1 :] + longer)
    if kind == "ssn":
        return str(1 + draw.below(8)) + draw.like(canon[1:] + longer)
    if kind == "iban":
        body = "".join(str(draw.below(10)) if c.isdigit() else chr(65 + draw.below(26)) for c in canon[4:] + longer)
        return canon[:2] + f"{98 - _mod97(canon[:2] + '00' + body):02d}" + body
    gender, name = canon.split(":", 1)
    form, words = script(name), name.split(" ")
    known = gender if gender != "n" else "mf"[draw.below(2)]
    pool = [g for g in GIVEN[form, known] if g.casefold() not in words]
    given = pool[draw.below(len(pool))]
    family = "".join(SYLLABLES[form][draw.below(len(SYLLABLES[form]))] for _ in range(4 + len(longer)))
    return f"{gender}:{(given + ' ' + family if len(words) > 1 else family).casefold()}"


def render(mention: str, kind: str, canon: str, fake: str) -> str:
    """A surrogate in the mention's own format."""
    if kind == "name":
        words, like = fake.split(":", 1)[1].split(" "), mention.split(" ")
        upper = mention.isupper() and len(mention) > 1
        own = canon.split(":", 1)[1].split(" ")
        if len(like) == 1 and len(own) > 1 and like[0].casefold() == own[0] != own[-1]:
            words = words[:1]
        return " ".join(w.upper() if upper else w.capitalize() for w in words[-len(like) :])
    if kind in ("email", "ip"):
        return "".join(c.upper() if k < len(mention) and mention[k].isupper() else c for k, c in enumerate(fake)) if kind == "email" else fake
    rest, out = list(fake), []
    for c in mention:
        out.append(rest.pop(0) if c.isalnum() and rest else c)
    return "".join(out + rest)


Attempts = dict[tuple[str, str], int]


def fake_of(m: Mention, attempts: Attempts, key: bytes, full: frozenset[int]) -> str:
    domain = attempts.get(("domain", m.canon.rsplit("@", 1)[1]), 0) if m.kind == "email" else 0
    return surrogate(m.kind, m.canon, attempts.get((m.kind, m.canon), 0), key, domain, full)


def rewrite_text(text: str, attempts: Attempts, key: bytes, full: frozenset[int] = frozenset()) -> tuple[str, dict[str, int]]:
    """The text with surrogates, and the mentions per kind."""
    found = mentions(text)
    counts = dict.fromkeys(KINDS, 0)
    if not found:
        return text, counts
    out, at = [], 0
    for m in found:
        counts[m.kind] += 1
        out += [text[at : m.start], render(text[m.start : m.end], m.kind, m.canon, fake_of(m, attempts, key, full))]
        at = m.end
    return "".join([*out, text[at:]]), counts


def known_of(text: str) -> set[tuple[str, str]]:
    """Entities of a text; the domain of an address is one of its own."""
    found = {(m.kind, m.canon) for m in mentions(text)}
    return found | {("domain", c.rsplit("@", 1)[1]) for k, c in found if k == "email"}


def entities(docs: DataFrame, text: str = "text") -> DataFrame:
    """The distinct (kind, canon) of all documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            known = {x for t in batch.column(0).to_pylist() if t for x in known_of(t)}
            yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in known], pa.string()), pa.array([c for _, c in known], pa.string())], names=["kind", "canon"])

    return docs.select(F.col(f"`{text}`").alias("text")).mapInArrow(run, "kind string, canon string").distinct()


def _drawn(rows: DataFrame, key: bytes) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = [surrogate(k, c, a, key, d) for k, c, a, d in zip(*[batch.column(i).to_pylist() for i in range(4)], strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(values, pa.string())], names=["kind", "canon", "attempt", "domain", "fake"])

    return rows.select("kind", "canon", "attempt", "domain").mapInArrow(run, "kind string, canon string, attempt int, domain int, fake string")


def full_networks(known: DataFrame) -> frozenset[int]:
    """First addresses of the private networks of which over a quarter are entities."""
    part = lambda k: F.element_at(F.split("canon", r"\."), k).cast("int")
    a, b = part(1), part(2)
    rows = known.where("kind = 'ip'").select(F.when(a.isin(10, 127), F.concat(a, F.lit(".0.0.0"))).when((a == 192) & (b == 168), F.lit("192.168.0.0")).when((a == 172) & b.between(16, 31), F.lit("172.16.0.0")).alias("net"))
    counts = rows.where("net IS NOT NULL").groupBy("net").count().collect()  # four rows at most
    return frozenset(network(r["net"])[0] for r in counts if 4 * r["count"] > network(r["net"])[1])


def _draw_apart(known: DataFrame, store: Store, name: str, key: bytes) -> DataFrame:
    """kind, canon, attempt, fake: no two share a surrogate of their kind, none is an entity."""
    done, open_, turn = None, known.withColumn("attempt", F.lit(0)), 0
    taken = known.select(F.col("kind").alias("__k"), F.col("canon").alias("__c")).withColumn("__taken", F.lit(True))
    while True:
        drawn = _drawn(open_, key).withColumn("old", F.lit(0))
        both = drawn if done is None else drawn.unionByName(done.withColumn("old", F.lit(1)))
        # The first of those with one surrogate wins: an aggregate, and few rows in any group.
        order = F.struct((1 - F.col("old")).alias("new"), F.col("canon"))
        first = both.groupBy("kind", "fake").agg(F.min(order)["canon"].alias("first")).select(F.col("kind").alias("__fk"), F.col("fake").alias("__f"), "first")
        judged = both.join(first, (F.col("kind") == F.col("__fk")) & (F.col("fake") == F.col("__f"))).join(taken, (F.col("kind") == F.col("__k")) & (F.col("fake") == F.col("__c")), "left")
        judged = judged.withColumn("wins", (F.col("first") == F.col("canon")) & F.col("__taken").isNull()).select("kind", "canon", "attempt", "domain", "fake", "wins")
        judged = store.put(f"drawn_{name}{turn}", judged)
        done, lost = judged.where("wins").drop("wins"), judged.where("NOT wins")
        if lost.isEmpty():
            return done.select("kind", "canon", "attempt", "fake")
        if turn == MOST:
            raise RuntimeError(f"no free surrogates for {lost.select('kind').first()[0]} entities after {MOST} draws")
        open_, turn = lost.select("kind", "canon", "domain", (F.col("attempt") + 1).alias("attempt")), turn + 1


def resolve(known: DataFrame, store: Store, key: bytes, full: frozenset[int] = frozenset()) -> DataFrame:
    """kind, canon, attempt, fake of all entities but those of full networks."""
    zero = F.lit(0).alias("domain")
    domains = _draw_apart(known.where("kind = 'domain'").select("kind", "canon", zero), store, "domain", key)
    again = domains.where("attempt > 0").select(F.col("canon").alias("__d"), F.col("attempt").alias("__a"))
    place = F.substring_index("canon", "@", -1)
    mails = known.where("kind = 'email'").join(again, place == F.col("__d"), "left").select("kind", "canon", F.coalesce("__a", F.lit(0)).alias("domain"))
    rest = known.where("kind NOT IN ('domain', 'email')").select("kind", "canon", zero)
    for first in sorted(full):
        prefix = {1 << 24: 1, 1 << 16: 2, 1 << 20: 1}[network(_dotted(first))[1]]
        own = F.substring_index("canon", ".", prefix) == ".".join(_dotted(first).split(".")[:prefix])
        if first >> 24 == 172:
            own = own & F.element_at(F.split("canon", r"\."), 2).cast("int").between(16, 31)
        rest = rest.where(~((F.col("kind") == "ip") & own))
    return domains.unionByName(_draw_apart(mails.unionByName(rest), store, "entity", key))


def rewrite(docs: DataFrame, key: bytes, text: str = "text") -> DataFrame:
    """The rows with surrogates in their text, and ``n_<kind>`` columns (in place of input columns of these names)."""
    if not key:
        raise ValueError("surrogates need a key")
    store, spark = Store(docs.sparkSession), docs.sparkSession
    known = store.put("entities", entities(docs, text))
    full = full_networks(known)
    again = store.put("again", resolve(known, store, key, full).where("attempt > 0").select("kind", "canon", "attempt"))
    store.keep("again")
    n, cols = again.count(), docs.columns
    row = docs.select(F.struct(*[F.col(f"`{c}`") for c in cols if c != text]).alias("row"), F.col(f"`{text}`").alias("text"))
    if n <= SMALL:
        shared = spark.sparkContext.broadcast({(r["kind"], r["canon"]): r["attempt"] for r in again.collect()})
        row = row.withColumn("again", F.lit(None).cast("array<struct<kind: string, canon: string, attempt: int>>"))
    else:  # attach to each text the attempts of its own entities
        shared = spark.sparkContext.broadcast({})
        own = _own_entities(row).join(again, ["kind", "canon"]).groupBy("text_key").agg(F.collect_set(F.struct("kind", "canon", "attempt")).alias("again"))
        row = row.withColumn("text_key", F.sha2("text", 256)).join(own, "text_key", "left").select("row", "text", "again")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, counts = [], []
            for t, own in zip(batch.column("text").to_pylist(), batch.column("again").to_pylist(), strict=True):
                attempts = shared.value if own is None else {(a["kind"], a["canon"]): a["attempt"] for a in own}
                fresh, n_kind = rewrite_text(t, attempts, key, full) if t else (t, dict.fromkeys(KINDS, 0))
                texts.append(fresh)
                counts.append(n_kind)
            numbers = [pa.array([c[k] for c in counts], pa.int64()) for k in KINDS]
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(texts, pa.string()), *numbers], names=["row", "text", *[f"n_{k}" for k in KINDS]])

    schema = f"row {row.schema['row'].dataType.simpleString()}, text string, " + ", ".join(f"n_{k} long" for k in KINDS)
    done, made = row.mapInArrow(run, schema), [f"n_{k}" for k in KINDS]
    return done.select(*[F.col("text").alias(text) if c == text else F.col("row")[c].alias(c) for c in cols if c not in made], *made)


def _own_entities(rows: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [(k, *x) for k, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) if t for x in known_of(t)]
            yield pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], pa.string()) for i in range(3)], names=["text_key", "kind", "canon"])

    return rows.select(F.sha2("text", 256).alias("text_key"), "text").mapInArrow(run, "text_key string, kind string, canon string").distinct()
