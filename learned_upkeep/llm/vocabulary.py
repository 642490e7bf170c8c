"""Token identifiers of whole texts by the tokenizers library, with each distinct chunk encoded once.

Both vocabularies cut a text before a space that stands between two other characters: no token
crosses it.  So the identifiers of a text are those of its chunks in order, and a bounded memory of
chunks replaces most calls of the library.  Chunks of letters alone go straight to the library's
model, since they are one pre-token.  Identifiers are kept as little-endian uint32 bytes.

A column of texts is encoded at once (:meth:`Encoder.encode_all`): Arrow cuts it into chunks and tells
the distinct ones, so Python sees each distinct chunk of a block once instead of every word.
"""

from __future__ import annotations

import re
import string
import sys
import unicodedata
from array import array
from functools import cached_property, lru_cache

import numpy as np
import pyarrow as pa

#: Chunks of columns that one worker remembers: half of them since the last change of generations, half before it.
MEMORY = 500_000
#: The same for vocabularies that drop white space and case, whose workers live on between the stages of a pipeline.
FOLDED_MEMORY = 200_000
#: The same for each kind of chunks of single texts, and of words within chunks.
SINGLE_MEMORY = 100_000
_BOUNDARY = re.compile(r"(?<=\S) (?=\S)")
#: Letters with a tail of ASCII punctuation.
_TAIL = re.compile(r"([^!-@\[-`{-~]+)([!-/:-@\[-`{-~]+)")
#: Characters that Python takes for white space and the vocabularies don't.
_SEPARATORS = re.compile("[\x1c-\x1f]")
#: Bytes of text that are encoded at once: with 8 MB a worker took 100 MB more, in the same time.
ENCODED_BYTES = 2 << 20
#: White space that cuts a column of texts, by its byte.
_WHITE = np.isin(np.arange(256), [9, 10, 13, 32])
#: ASCII capitals to small letters, by their byte.
_FOLDED = np.frombuffer(bytes(range(256)).lower(), "uint8")
#: ASCII letters, digits and punctuation, by their byte: no pre-token holds two of them.  An apostrophe may start a contraction.
_KIND = np.zeros(256, "uint8")
for _k, _c in enumerate((string.ascii_letters, string.digits, string.punctuation.replace("'", "")), 1):
    _KIND[list(_c.encode())] = _k
#: Stands for the identifiers of a chunk that can't be read by itself; no identifiers have its length.
_ODD = b"?"


def _packed(ids: list[int]) -> bytes:
    """Little-endian uint32 bytes."""
    a = array("I", ids)
    if sys.byteorder == "big":
        a.byteswap()
    return a.tobytes()


def single_spaced(text: str) -> list[str] | None:
    """The words of a text whose only white space is single spaces and line feeds between other characters; None of any other text."""
    words = text.split()
    return words if words and " ".join(words) == text.replace("\n", " ") else None


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class _Memory(dict):
    """Identifiers of chunks, learnt when first asked for; chunks that a whole generation didn't ask for are forgotten."""

    def __init__(self, learn, most: int = MEMORY) -> None:
        super().__init__()
        self.learn, self.older, self.most = learn, {}, most

    def __missing__(self, chunk: str) -> bytes:
        if len(self) >= self.most // 2:
            self.older = dict(self)
            self.clear()
        ids = self.older.get(chunk)
        if ids is None:
            ids = self.learn(chunk)
        self[chunk] = ids
        return ids


@lru_cache(maxsize=4)
def encoder(path: str, end: int = 0) -> Encoder:
    """One encoder for all tasks of a worker process, so that its memory outlives a task."""
    return Encoder(path, end)


class Encoder:
    """Identifiers of whole texts as bytes; ``end`` is appended to each text."""

    def __init__(self, path: str, end: int = 0) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # their strings in a text are ordinary text
        self.model = self.tokenizer.model
        self.end = _packed([end])
        #: Vocabularies that drop white space and case read a chunk alike with and without its space.
        self.plain = self.tokenizer.normalizer is not None
        #: Pre-tokens of an ASCII chunk; the vocabularies differ in their digits.
        self.runs = re.compile("[A-Za-z]+|[0-9]|[^A-Za-z0-9]+" if self.plain else "[A-Za-z]+|[0-9]+|[^A-Za-z0-9]+")
        self.chunks = _Memory(self._alone, FOLDED_MEMORY if self.plain else MEMORY)
        self.bare = _Memory(lambda c: self._learn("", c), SINGLE_MEMORY)
        self.spaced = self.bare if self.plain else _Memory(lambda c: self._learn(" ", c), SINGLE_MEMORY)

    @cached_property
    def _byte_names(self) -> list[str]:
        """The printable stand-in of each byte in byte-level vocabularies: itself if printable, else the next code point from 256."""
        own = {*range(33, 127), *range(161, 173), *range(174, 256)}
        rest = iter(range(256, 512))
        return [chr(b if b in own else next(rest)) for b in range(256)]

    def _learn(self, space: str, chunk: str) -> bytes:
        if chunk.isalpha():
            if self.plain:
                low = chunk.lower()
                if chunk.isascii() or unicodedata.is_normalized("NFC", chunk) and len(low) == len(chunk) and "Σ" not in chunk:
                    return self.bare[low] if low != chunk else self._tokens(chunk)
            else:
                return self._tokens(space + chunk)
        elif "'" not in chunk:  # else contractions are cut in another way
            if (m := _TAIL.fullmatch(chunk)) and m[1].isalpha() and (m[1].isascii() or not self.plain or self._letters(m[1])):
                return (self.bare[m[1]] if self.plain else self.chunks[space + m[1]]) + self._tail(m[2])
            if chunk.isascii() and chunk.isprintable() and " " not in chunk:
                first, *more = self.runs.findall(chunk.lower() if self.plain else chunk)
                return self._tokens(first if self.plain else space + first) + b"".join(map(self._tokens, more))
        return self._whole(space + chunk)

    @staticmethod
    def _letters(word: str) -> bool:
        """True if the vocabularies that fold case read nothing but letters: some capitals fold to a letter and a mark."""
        return unicodedata.is_normalized("NFC", word) and word.lower().isalpha()

    def _tokens(self, word: str) -> bytes:
        if word.isascii():  # printable characters stand for themselves
            name = "Ġ" + word[1:] if word[0] == " " else word
        else:
            names = self._byte_names
            name = "".join([names[b] for b in word.encode()])
        return _packed([t.id for t in self.model.tokenize(name)])

    def _tail(self, marks: str) -> bytes:
        return self.bare[marks] if len(marks) == 1 else self._tokens(marks)

    def _whole(self, text: str) -> bytes:
        return _packed(self.tokenizer.encode(text, add_special_tokens=False).ids)

    def encode(self, text: str) -> bytes:
        if not text:
            return self.end
        if self.plain and not _SEPARATORS.search(text):
            return b"".join(map(self.bare.__getitem__, text.split())) + self.end
        words = single_spaced(text)
        if words is None:
            at = [0, *[m.start() for m in _BOUNDARY.finditer(text)], len(text)]
            parts = [self._odd(text[a:b]) for a, b in zip(at, at[1:], strict=False)]
            return b"".join(parts) + self.end
        bare, spaced, lines, at = self.bare.__getitem__, self.spaced.__getitem__, [], 0
        for line in text.split("\n"):  # a line feed is a token of its own
            upto = at + line.count(" ") + 1
            lines.append(bare(words[at]) + b"".join(map(spaced, words[at + 1 : upto])))
            at = upto
        return self.bare["\n"].join(lines) + self.end

    def encode_all(self, texts: pa.Array) -> pa.ListArray:
        """For each text of an Arrow column of strings (null: empty) what :meth:`encode` gives, as a list of int32.

        Of a run of white space all but the last character are one pre-token; a last space belongs to
        the word behind it, any other last character is a pre-token.  So chunks cut there, and between
        ASCII letters, digits and punctuation, are read alike alone and in their text.  Texts with
        other white space go to :meth:`encode`.
        """
        texts = texts.fill_null("").cast(pa.string())
        n = len(texts)
        at = np.frombuffer(texts.buffers()[1], "int32", n + 1, 4 * texts.offset) if n else np.zeros(1, "int32")
        body = texts.buffers()[2] if at[-1] > at[0] else None
        if body is None:
            return self._lists([self.end] * n)
        body, at = body.slice(int(at[0]), int(at[-1] - at[0])), at - at[0]
        raw = np.frombuffer(body, "uint8")
        if self.plain:
            folded, kept = _FOLDED[raw], np.flatnonzero(raw[1:] >= 128)
            folded[kept] = raw[kept]  # a mark that follows may join with the capital only
            raw, body = folded, pa.py_buffer(folded)
        cut = np.zeros(raw.size + 1, bool)
        cut[at] = True
        white = _WHITE[raw]
        last = white.copy()
        last[:-1] &= ~(white[1:] | cut[1:-1])  # before another character of the same text
        last[-1] = False
        cut[:-1] |= last
        cut[1:] |= last & (raw != 32)
        white[1:] &= ~white[:-1]
        cut[:-1] |= white  # the first of a run
        kind = _KIND[raw]
        cut[1:-1] |= (kind[1:] != kind[:-1]) & (kind[1:] > 0) & (kind[:-1] > 0)
        marks = np.flatnonzero(cut).astype("int32")
        coded = pa.StringArray.from_buffers(marks.size - 1, pa.py_buffer(marks), body).dictionary_encode()
        found = list(map(self.chunks.__getitem__, coded.dictionary.to_numpy(zero_copy_only=False).tolist()))
        which, upto = coded.indices.to_numpy(), np.searchsorted(marks, at)
        ends = np.full(n, len(found))
        odd = np.fromiter((x is _ODD for x in found), bool, len(found))
        found.append(self.end)
        if odd.any():
            bad = np.unique(np.searchsorted(upto, np.flatnonzero(odd[which]), "right") - 1)
            ends[bad] = len(found) + np.arange(bad.size)
            found = [b"" if x is _ODD else x for x in found]
            found += [self.encode(t) for t in texts.take(pa.array(bad)).to_pylist()]
            sizes = np.diff(upto)
            which = which[~np.repeat(np.isin(np.arange(n), bad), sizes)]
            sizes[bad] = 0
            upto = np.concatenate([[0], np.cumsum(sizes)])
        whole = self._lists(found).take(pa.array(np.insert(which, upto[1:], ends)))
        return pa.ListArray.from_arrays(whole.offsets.take(pa.array(upto + np.arange(n + 1))), whole.values)

    @staticmethod
    def _lists(encoded: list[bytes]) -> pa.ListArray:
        ends = np.cumsum([0, *map(len, encoded)]) // 4
        return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.frombuffer(b"".join(encoded), "<i4")))

    def _alone(self, chunk: str) -> bytes:
        """Identifiers of a chunk of :meth:`encode_all`: a word or a part of one, with or without a space before it, or white space."""
        space, word = (" ", chunk[1:]) if chunk[0] == " " else ("", chunk)
        if word.isalpha() and not self.plain:
            return self._tokens(chunk)
        if word.split() == [word]:
            return self._learn("" if self.plain else space, word)
        return _ODD if chunk.strip(" \t\n\r") else b"" if self.plain else self._whole(chunk)

    def _odd(self, part: str) -> bytes:
        return self.spaced[part[1:]] if part[0] == " " and len(part) > 1 and not part[1].isspace() else self.bare[part]
