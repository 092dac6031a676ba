"""Whole-text encoding with a public tokenizer file, through a bounded cache.

A text is cut before every single space that follows a character other than white
space.  The byte-level pre-tokenizer always ends a piece there, and nothing before the
cut changes what follows it, so the ids of a text are the ids of its parts in order.
Parts repeat; short ones are encoded by the library once per cache, which is bounded by
its bytes.  A text in which white
space precedes a space, or that holds the string of an added token, is encoded whole.
"""

from __future__ import annotations

import functools
import itertools
import os
import re
import sys
from array import array
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: The default vocabulary file, bytes of each of a cache's two generations, bytes of an entry
#: besides its contents, characters of the longest part that is kept, and of texts whose parts are told apart together.
VOCABULARY, CACHE, ENTRY, KEPT, TOGETHER = "byte_bpe_50k.json", 100 << 20, 200, 64, 4 << 20
#: White space that makes a text unsafe to cut, before a space or anywhere.
_BEFORE_SPACE = ("  ", "\n ", "\t ", "\r ")
_ANYWHERE = tuple(map(chr, [0x0B, 0x0C, *range(0x1C, 0x20), 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]))


def vocabulary_path(name: str = VOCABULARY) -> str:
    """A path as given, or the place of a public file of that name."""
    if os.sep in name:
        return name
    import public_tokenizers

    return public_tokenizers.path(name)


@functools.cache
def tokenizer(name: str = VOCABULARY):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    return Tokenizer.from_file(vocabulary_path(name))


@functools.cache
def span_tokenizer(name: str = VOCABULARY):
    """The same, with spans that keep the white space of a token."""
    from tokenizers import Tokenizer, processors

    found = Tokenizer.from_file(vocabulary_path(name))
    found.post_processor = processors.ByteLevel(trim_offsets=False)
    return found


class _Values(dict):
    """Values by part; a missing one is taken from the generation before or made.

    Long parts are not kept, and none is once the generation is full.  ``make`` gets a part
    without the space before it.
    """

    def __init__(self, make: Callable[[str], bytes], before: dict[str, bytes], room: int) -> None:
        super().__init__()
        self.make, self.before, self.room = make, before, room

    def __missing__(self, part: str) -> bytes:
        found = self.before.get(part)
        if found is None:
            found = self.make(part)
        if self.room > 0 and len(part) <= KEPT:
            self[part] = found
            self.room -= ENTRY + len(part) + len(found)
        return found


    def take(self, fresh: dict[str, bytes]) -> None:
        """Keeps values that were made elsewhere, as far as there is room."""
        short = {part: value for part, value in fresh.items() if len(part) <= KEPT}
        size = ENTRY * len(short) + sum(map(len, short)) + sum(map(len, short.values()))
        if size > max(self.room, 0):
            short = dict(itertools.islice(short.items(), max(self.room, 0) * len(short) // size))
            size = self.room
        self.update(short)
        self.room -= size


class Parts:
    """Values of texts' parts; ``whole`` maps any text to bytes, ``part`` one without added tokens."""

    def __init__(self, whole: Callable[[str], bytes], special: Sequence[str], size: int = CACHE) -> None:
        self.whole, self.special, self.size = whole, tuple(special), size
        self.known = _Values(self.behind, {}, size)

    def part(self, string: str) -> bytes:
        return self.whole(string)

    def behind(self, part: str) -> bytes:
        """The value of a part behind its space."""
        return self.part(f" {part}")

    def safe(self, text: str) -> bool:
        """Whether the text may be cut."""
        for x in _BEFORE_SPACE:
            if x in text:
                return False
        for x in _ANYWHERE:
            if x in text:
                return False
        for x in self.special:
            if x in text:
                return False
        return True

    def split(self, text: str) -> list[str]:
        """The text's parts without their leading space (the first has none); an unsafe text is one."""
        return text.split(" ") if self.safe(text) else [text]

    def _turn(self) -> None:
        """Starts a new generation when the present one is full."""
        if self.known.room <= 0:
            full = self.known
            full.before = {}
            self.known = _Values(self.behind, full, self.size)

    def of(self, text: str) -> tuple[list[str], list[bytes]]:
        """The parts of a text and their values."""
        self._turn()
        parts = self.split(text)
        return parts, [self.whole(parts[0]), *map(self.known.__getitem__, parts[1:])]

    def joined(self, text: str) -> bytes:
        """The values of a text's parts, one behind the other."""
        self._turn()
        parts = self.split(text)
        head = self.whole(parts[0])
        return head + b"".join(map(self.known.__getitem__, parts[1:])) if len(parts) > 1 else head


def _byte_letters() -> dict[int, str]:
    """Byte-level alphabet: printable bytes stand for themselves, the others for U+0100 on."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in own]
    return {b: chr(b) for b in own} | {b: chr(0x100 + k) for k, b in enumerate(rest)}


class IdParts(Parts):
    """Parts whose values are ids; a part's pieces go through the library's model.

    The pre-tokenizer's rule is applied here.  Parts outside a plain range of
    characters, in which the rule's character classes do not depend on a Unicode
    version, are encoded by the library as a whole.
    """

    #: The byte-level pre-tokenizer's pattern and the plain range.
    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
    PLAIN = re.compile("[\\t\\n\\r -~\u00a1-\u024f]*")

    def __init__(self, name: str, size: int = CACHE) -> None:
        import regex

        if array("I").itemsize != 4 or sys.byteorder != "little":
            raise RuntimeError("needs 32-bit little-endian arrays")
        tok = self.tok = tokenizer(name)
        super().__init__(lambda text: array("I", tok.encode(text, add_special_tokens=False).ids).tobytes(), added_tokens(tok), size)
        self.find, self.match, self.tokenize = regex.compile(self.PATTERN).findall, self.PLAIN.fullmatch, tok.model.tokenize
        self.letters = _byte_letters()
        self.space = self.letters[0x20]
        plain = [c for c in map(chr, range(0x250)) if self.match(c)]
        self.spelled = {ord(c): c.encode().decode("latin-1").translate(self.letters) for c in plain}
        self.word = re.compile(f" [{''.join(c for c in plain if c.isalpha())}]+").match
        self.inner, self.inner_room = {}, size // 4

    def piece(self, piece: str) -> bytes:
        return array("I", [t.id for t in self.tokenize(piece.translate(self.spelled))]).tobytes()

    def behind(self, part: str) -> bytes:
        # Letters are one piece.
        if part.isalpha():
            if part.isascii():
                return array("I", [t.id for t in self.tokenize(self.space + part)]).tobytes()
            if self.match(part):
                return array("I", [t.id for t in self.tokenize(self.space + part.translate(self.spelled))]).tobytes()
        return self.part(f" {part}")

    def within(self, piece: str) -> bytes:
        """A piece that is no part of its own."""
        value = self.inner.get(piece)
        if value is None:
            value = self.piece(piece)
            if len(piece) <= KEPT:
                if self.inner_room <= 0:
                    self.inner, self.inner_room = {}, self.size // 4
                self.inner[piece] = value
                self.inner_room -= ENTRY + len(piece) + len(value)
        return value

    def each(self, texts: Sequence[str | None]) -> Iterator[bytes]:
        """What ``joined`` gives for every text; a part is looked up once for all texts of a chunk."""
        at = 0
        while at < len(texts):
            heads, tails, held = [], [], 0
            while at < len(texts) and held < TOGETHER:
                text = texts[at] or ""
                cut = text.find(" ") if self.safe(text) else -1
                heads.append(self.whole(text if cut < 0 else text[:cut]))
                tails.append(None if cut < 0 else text[cut + 1 :])
                held += len(text)
                at += 1
            yield from self._together(heads, tails)

    def _values(self, names: list[str]) -> list[bytes]:
        """The values of distinct parts; those without one get theirs together."""
        known, before, fresh = self.known, self.known.before, {}
        values = list(map(known.get, names))
        absent = [k for k, v in enumerate(values) if v is None]
        for k in absent:
            if (found := before.get(names[k])) is not None:
                values[k] = fresh[names[k]] = found
        absent = [k for k in absent if values[k] is None]
        words = [k for k in absent if names[k].isalpha() and self.match(names[k])]
        spelled = " ".join([names[k] for k in words]).translate(self.spelled).split(self.space)
        tokens = [self.tokenize(self.space + x) for x in spelled] if words else []
        ids, at = array("I", [t.id for x in tokens for t in x]).tobytes(), 0
        for k, x in zip(words, tokens, strict=True):
            to = at + 4 * len(x)
            values[k] = fresh[names[k]] = ids[at:to]
            at = to
        known.take(fresh)
        for k in absent:
            if values[k] is None:
                values[k] = known[names[k]]
        return values

    def _together(self, heads: list[bytes], tails: list[str | None]) -> Iterator[bytes]:
        self._turn()
        split = pc.split_pattern(pa.array(tails, pa.string()), " ")
        many = pc.fill_null(pc.list_value_length(split), 0).to_numpy(zero_copy_only=False)
        parts = split.flatten().dictionary_encode()
        # No part holds a space: one string of all is cut faster than they are read one by one.
        distinct = parts.dictionary
        names = pc.binary_join(pa.ListArray.from_arrays([0, len(distinct)], distinct), " ")[0].as_py().split(" ") if len(distinct) else []
        values = [*self._values(names), *heads]
        size = np.fromiter(map(len, values), np.int64, len(values)) // 4
        first = np.cumsum(size) - size
        # A text's head, then its parts.
        entry = np.empty(len(parts) + len(heads), np.int64)
        ends = np.cumsum(many + 1)
        place = ends - many - 1
        is_part = np.ones(len(entry), bool)
        is_part[place] = False
        entry[is_part] = parts.indices.to_numpy()
        entry[place] = np.arange(len(values) - len(heads), len(values))
        n = size[entry]
        until = np.cumsum(n)
        ids = np.frombuffer(b"".join(values), "<u4")[np.arange(until[-1]) + np.repeat(first[entry] - until + n, n)].tobytes()
        edges = [0, *(4 * until[ends - 1]).tolist()]
        yield from (ids[a:b] for a, b in zip(edges, edges[1:]))  # noqa: B905

    def part(self, string: str) -> bytes:
        if not self.match(string):
            return self.whole(string)
        # Letters end a piece where they end, whatever follows; what follows is searched for its own pieces.
        word = self.word(string)
        if word is None:
            return self.pieces(string)
        at = word.end()
        if at == len(string):
            return self.piece(string)
        rest = string[at:]
        return self.known[string[1:at]] + (self.inner.get(rest) or self.pieces(rest))

    def pieces(self, string: str) -> bytes:
        found = self.find(string)
        if len(found) == 1:
            return self.piece(string) if string[0] == " " else self.within(string)
        return b"".join([self.known[p[1:]] if p[0] == " " and len(p) > 1 else self.within(p) for p in found])


def added_tokens(tok) -> list[str]:
    return [t.content for t in tok.get_added_tokens_decoder().values()]


@functools.cache
def id_parts(name: str = VOCABULARY) -> IdParts:
    """Parts whose values are their ids, little-endian unsigned 32-bit; one cache per worker process."""
    return IdParts(name)


def forget() -> None:
    """Drops this process's caches of ids: idle workers stay, with what they hold."""
    id_parts.cache_clear()


@functools.cache
def span_parts(name: str = VOCABULARY) -> Parts:
    """Parts whose values are their tokens' (start, end) characters, int32 pairs; one cache per worker process."""
    tok = span_tokenizer(name)

    def encode(string: str) -> bytes:
        return np.array(tok.encode(string, add_special_tokens=False).offsets, dtype=np.int32).tobytes()

    return Parts(encode, added_tokens(tok))


def spans_of(parts: list[str], values: list[bytes]) -> np.ndarray:
    """(tokens, 2) character spans of a whole text from its parts."""
    flat = np.frombuffer(b"".join(values), dtype=np.int32).reshape(-1, 2)
    if len(parts) == 1:
        return flat
    length = np.fromiter(map(len, parts), dtype=np.int64, count=len(parts)) + 1
    length[0] -= 1
    count = np.fromiter(map(len, values), dtype=np.int64, count=len(values)) // 8
    return flat + np.repeat(np.cumsum(length) - length, count)[:, None]
