"""Loading of the public vocabulary files, once in each Python worker. The folder is a parameter."""

from __future__ import annotations

import base64
import functools
import re
import unicodedata
from collections.abc import Callable

import numpy as np

# Characters that all Unicode versions and both regular expression libraries class alike, which leaves out
# superscripts and fractions; texts with others are encoded whole.
_AGREED = re.compile("[\\x00-\u00b1\u00b4-\u00b8\u00ba\u00bb\u00bf-\u024f\u0391-\u03a1\u03a3-\u03c9\u0410-\u044f\u2010-\u2027\u3041-\u3096\u30a1-\u30fa\u4e00-\u9fa5]*")

_SEPARATORS = "\x1c\x1d\x1e\x1f\x85"  # white space to one of the libraries only


def vocabulary_path(name: str, folder: str | None = None) -> str:
    if folder:
        return f"{folder.rstrip('/')}/{name}"
    import public_tokenizers

    return public_tokenizers.path(name)


def split_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


def _agreed(text: str) -> bool:
    """Whether both regular expression libraries class all characters of the text alike."""
    return (text.isascii() or _AGREED.fullmatch(text) is not None) and not any(c in text for c in _SEPARATORS)


def _ranges(named: str) -> str:
    """The agreed characters of a class, as ranges of code points."""
    import regex

    is_in = regex.compile(named).fullmatch
    points = [i for i in range(1 << 16) if is_in(chr(i)) and _agreed(chr(i))]
    starts = [i for k, i in enumerate(points) if not k or points[k - 1] != i - 1]
    ends = [i for k, i in enumerate(points) if k + 1 == len(points) or points[k + 1] != i + 1]
    return "".join(f"\\u{a:04x}-\\u{b:04x}" for a, b in zip(starts, ends, strict=True))


@functools.cache
def cutter(pattern: str) -> Callable[[str], list[str]]:
    """The pieces of a text by the pattern. Texts that _agreed() admits are cut by the standard library, which
    takes half the time where classes are spelled out as ranges; texts with others by the pattern as it is."""
    import regex

    sets = {name: _ranges(name) for name in (r"\p{L}", r"\p{N}", r"\s")}

    def spelled(m: re.Match) -> str:
        part = m[0]
        if part.startswith("["):
            for name, own in sets.items():
                part = part.replace(name, own)
            return part
        return f"[^{sets[part.lower()]}]" if part == r"\S" else f"[{sets[part]}]"

    usual = re.compile(re.sub(r"\[[^\]]*\]|\\p\{[LN]\}|\\[sS]", spelled, pattern)).findall
    every = regex.compile(pattern).findall
    return lambda text: (usual if _agreed(text) else every)(text)


@functools.cache
def ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in f if line.strip())}


@functools.cache
def byte_encoder(path: str, pattern: str):
    """A byte-level encoder, and the byte length of each id."""
    import tiktoken

    table = ranks(path)
    sizes = np.zeros(max(table.values()) + 1, dtype=np.int64)
    for token, rank in table.items():
        sizes[rank] = len(token)
    return tiktoken.Encoding("byte-level", pat_str=pattern, mergeable_ranks=table, special_tokens={}), sizes


class WordEncoder:
    """Ids of the lower-cased word vocabulary, as little-endian bytes, from a bounded memory of words.

    The file's own steps are kept: canonical composition, white space to blanks, lower case letter by
    letter, pieces by the file's pattern, then merges. Only the merges run in the library, once for each
    word not remembered; so the result equals encoding the whole text."""

    # The vocabulary file's pattern for the texts that _AGREED admits: letters, single digits, other marks.
    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\s\w]|_)+"

    def __init__(self, path: str, remembered: int = 100_000):
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self._path, self._whole = path, None
        self._merges = Tokenizer.from_file(path)
        self._merges.encode_special_tokens = True
        self._merges.normalizer = normalizers.Sequence([])
        self._merges.pre_tokenizer = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        self._pieces = re.compile(self.PATTERN).findall
        self._remembered = remembered
        self._known: dict[str, bytes] = {}
        self._before: dict[str, bytes] = {}

    def words(self, text: str) -> list[str]:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("\u03a3", "\u03c3")
        return self._pieces(text.lower())

    def ids(self, text: str) -> bytes:
        if not _agreed(text):
            if self._whole is None:
                from tokenizers import Tokenizer

                self._whole = Tokenizer.from_file(self._path)
                self._whole.encode_special_tokens = True
            return np.array(self._whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        words = self.words(text)
        parts = list(map(self._known.get, words))
        if None not in parts:
            return b"".join(parts)
        if len(self._known) > self._remembered:  # the words of the generation before are still looked up
            self._before, self._known = self._known, {}
        known, old, new = self._known, self._before, []
        for w in {w for w, p in zip(words, parts, strict=True) if p is None}:
            if w in old:
                known[w] = old[w]
            else:
                new.append(w)
        for low in range(0, len(new), 4096):
            some = new[low : low + 4096]
            for w, e in zip(some, self._merges.encode_batch_fast(some, add_special_tokens=False), strict=True):
                known[w] = np.array(e.ids, "<u4").tobytes()
        return b"".join([known[w] if p is None else p for w, p in zip(words, parts, strict=True)])


@functools.cache
def word_encoder(path: str, remembered: int) -> WordEncoder:
    return WordEncoder(path, remembered)
