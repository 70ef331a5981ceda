"""Encoding long texts through a cache of short chunks.

Tokenizer libraries spend most of their time on strings they have met before. A text is cut
where no token can cross, each distinct chunk is encoded once by the library, and the chunks'
ids are joined. The cache is bounded by its bytes, so memory does not follow the input; results never depend on what is cached.
"""

from __future__ import annotations

import ctypes
import gc
import os
import re
from collections.abc import Callable, Iterable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa

#: What one generation of a worker's cache holds, as counted; two are alive at most.
CACHE_BYTES = 120_000_000
#: What an entry takes beside its text and ids.
_ENTRY = 200


def release_memory() -> None:
    """Give what a task no longer holds back to the system: workers outlive their tasks, and an
    executor counts the pages of all of them."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


@contextmanager
def uncollected() -> Iterator[None]:
    """Without Python's cycle collector: encoding makes millions of small objects and no cycles,
    and each pass over a full cache costs more than the encoding between two passes."""
    was = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if was:
            gc.enable()


class Generations:
    """A bounded cache in two generations: a full new one becomes the old one, and what is asked
    for again moves back. Frequent entries stay, and at most twice ``limit`` bytes are held."""

    def __init__(self, limit: int):
        self.limit = limit
        self.clear()

    def clear(self) -> None:
        self.new: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.size = 0

    def get(self, name: str) -> bytes | None:
        found = self.new.get(name)
        return self.old.get(name) if found is None else found

    def put(self, entries: dict[str, bytes]) -> None:
        if self.size > self.limit:
            self.old, self.new, self.size = self.new, {}, 0
        self.new |= entries
        self.size += sum(map(len, entries)) + sum(map(len, entries.values())) + _ENTRY * len(entries)

    def look_up(self, names: list[str], make: Callable[[list[str]], Iterable[bytes]]) -> list[bytes]:
        """The values of ``names``; ``make`` gives those of names not held."""
        found = list(map(self.new.get, names))
        if None not in found:
            return found
        own: dict[str, bytes] = {}
        fresh: dict[str, None] = {}
        for n, v in zip(names, found):
            if v is None:
                v = self.old.get(n)
                if v is None:
                    fresh[n] = None
                else:
                    own[n] = v
        own.update(zip(fresh, make(list(fresh))))
        self.put(own)
        return [own[n] if v is None else v for n, v in zip(names, found)]


class ChunkEncoder:
    """``split(text)`` gives chunks whose encodings join to that of the text; ``encode(list)``
    gives for each of a list of chunks its ids, packed as little-endian unsigned 32-bit. A text
    with one of the strings ``apart`` in it goes to ``whole`` instead, uncut."""

    def __init__(self, split: Callable[[str], list[str]], encode: Callable[[list[str]], Iterable[bytes]], cache: Generations | None = None, apart: Iterable[str] = (), whole: Callable[[str], list[int]] | None = None):
        self.split, self.encode, self.cache = split, encode, cache or Generations(CACHE_BYTES)
        self.apart, self.whole = tuple(apart), whole

    def __call__(self, text: str) -> np.ndarray:
        if self.whole is not None and any(a in text for a in self.apart):
            return np.array(self.whole(text), "<u4")
        return np.frombuffer(b"".join(self.cache.look_up(self.split(text), self.encode)), "<u4")

    def forget(self) -> None:
        """Let all chunks go: between tasks a worker holds the library's model only."""
        self.cache.clear()
        release_memory()


_BETWEEN_WORDS = re.compile(r"(?<=\S)(?= \S)")
_LONG_SPACE = re.compile(r"\s\s")


def split_before_single_spaces(text: str) -> list[str]:
    """Cuts before each single ASCII space between two non-space characters.

    The byte-level pattern attaches such a space to what follows it and matches nothing across
    the cut, so ids of the parts join to the ids of the whole.
    """
    if not text:
        return []
    if _LONG_SPACE.search(text) or text[0].isspace() or text[-1].isspace():
        return _BETWEEN_WORDS.split(text)
    first, *rest = text.split(" ")
    return [first, *[" " + r for r in rest]]


# Fixed value: how the byte-level vocabulary's pattern cuts a text before any merge.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def _visible_bytes() -> dict[int, int]:
    """The byte-level alphabet: printable Latin-1 stands for itself, the rest from 256 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    return {b: b for b in shown} | {b: 256 + i for i, b in enumerate(hidden)}


class ByteLevelLibrary:
    """The tokenizers library's model over the pattern's pieces.

    The library's own cutting and mapping of bytes costs more than its merges, so pieces are cut
    and mapped here and only new ones are merged, by the library's model. Chunks and pieces
    share one cache: a piece alone is a chunk with the same ids. Texts that hold an added token
    (the file's special strings) are left to the library whole.
    """

    def __init__(self, path: str, cache: Generations):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        import regex
        from tokenizers import Tokenizer

        self.library, self.cache = Tokenizer.from_file(path), cache
        self.model = self.library.model
        self.added = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.parts = regex.compile(PATTERN).findall
        self.alphabet = _visible_bytes()
        self.packed = [i.to_bytes(4, "little") for i in range(self.library.get_vocab_size())]

    def whole(self, text: str) -> list[int]:
        return self.library.encode(text, add_special_tokens=False).ids

    def _piece(self, piece: str) -> bytes:
        if piece.isascii() and piece[1:].isalpha() and piece[0] == " ":
            shown = "Ġ" + piece[1:]  # the alphabet's sign for a space
        else:
            shown = piece.encode().decode("latin-1").translate(self.alphabet)
        packed = self.packed
        return b"".join([packed[t.id] for t in self.model.tokenize(shown)])

    def _chunk(self, chunk: str, own: dict[str, bytes]) -> bytes:
        """A chunk is the pattern's pieces; words and words with one mark behind need no search."""
        body = chunk[1:] if chunk[0] == " " else chunk
        if body.isalpha():
            return self._piece(chunk)
        parts = (chunk[:-1], chunk[-1]) if chunk[-1] in ",." and body[:-1].isalpha() else self.parts(chunk)
        out = []
        for p in parts:
            ids = own.get(p) or self.cache.get(p)
            if ids is None:
                ids = own[p] = self._piece(p)
            out.append(ids)
        return b"".join(out)

    def __call__(self, chunks: list[str]) -> list[bytes]:
        own: dict[str, bytes] = {}
        found = [self._chunk(c, own) for c in chunks]
        self.cache.put(own)
        return found


_encoders: dict[str, ChunkEncoder] = {}


def byte_bpe_encoder(path: str) -> ChunkEncoder:
    """The encoder of a byte-level BPE file, made once in each Python worker."""
    if path not in _encoders:
        cache = Generations(CACHE_BYTES)
        library = ByteLevelLibrary(path, cache)
        _encoders[path] = ChunkEncoder(split_before_single_spaces, library, cache, library.added, library.whole)
    return _encoders[path]
