"""Fast whole-text encoding by BPE vocabularies that split a text at white space before any merge.

A text without irregular white space is the sequence of its pieces between single spaces, and each piece can be
encoded alone.  A batch of texts is split and dictionary-encoded by Arrow; only pieces that the worker has not met
are encoded, and the ids of all texts are then gathered with numpy.  Texts with irregular white space (two
white-space characters in a row of which one is a space, or separators on which libraries disagree) are encoded
whole.
"""

from __future__ import annotations

import gc
import os
import sys
import types
from collections.abc import Iterator
from itertools import chain
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: The white space of Unicode, as a class of RE2.
_SPACE = r"[\t-\r \x{85}\x{A0}\x{1680}\x{2000}-\x{200A}\x{2028}\x{2029}\x{202F}\x{205F}\x{3000}]"
IRREGULAR = rf" {_SPACE}|{_SPACE} |[\x{{1c}}-\x{{1f}}\x{{85}}\x{{180e}}\x{{200b}}\x{{feff}}]"
class Room(NamedTuple):
    """What a worker may hold (a matter of memory, not of results): pieces (beyond it only those that came in several
    slices of text stay, at most half as many), cut words, and bytes of text that are split at once."""

    pieces: int
    words: int
    slice_bytes: int


#: For a job of its own, about 0.6 GB a worker; and for a stage that shares its executors with other stages, 0.35 GB.
LARGE, SMALL = Room(600_000, 400_000, 8 << 20), Room(200_000, 150_000, 2 << 20)


def worker_state(key: tuple, make):
    """A value that tasks of one Python worker share (functions travel by value, so module globals are not shared)."""
    held = sys.modules.setdefault("_walkengine_worker_state", types.ModuleType("_walkengine_worker_state")).__dict__
    if key not in held:
        gc.set_threshold(300_000, 50, 50)  # the caches hold millions of objects that are no garbage; visit them rarely
        held[key] = make()
    return held[key]


def load_tokenizer(path: str):
    """The tokenizer in the file, with the strings of special tokens taken as ordinary text."""
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.encode_special_tokens = True
    tokenizer.no_truncation()
    tokenizer.no_padding()
    return tokenizer


def byte_slices(texts: pa.Array, limit: int) -> Iterator[tuple[int, pa.Array]]:
    """Runs of rows with about ``limit`` bytes of text each (a longer text is a run of its own)."""
    if not len(texts):
        return
    ends = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(texts), 0)).astype(np.int64))
    begin = 0
    while begin < len(texts):
        base = ends[begin - 1] if begin else 0
        end = max(begin + 1, int(np.searchsorted(ends, base + limit, side="right")))
        yield begin, texts.slice(begin, end - begin)
        begin = end


#: How the two kinds of vocabulary cut a piece before merging; in force for letters of Latin-1 only.
SPACED_CUT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
WORD_CUT = r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+"


def _byte_letters() -> dict[int, str]:
    """The printable letter that byte-level vocabularies write for each byte: itself where it is printable Latin-1,
    else the next free one from 256 on."""
    printable = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return {b: chr(b if b in printable else next(rest)) for b in range(256)}


class LibraryCodec:
    """Encodes pieces and whole texts with the ``tokenizers`` library.

    A piece of plain Latin-1 is cut here and each word given to the library's merge model once (its normaliser changes
    no such text but for case); any other piece goes through the whole tokenizer.
    """

    def __init__(self, path: str, spaced: bool, words: int = LARGE.words):
        import regex

        self.limit = words

        self.tokenizer, self.lower = load_tokenizer(path), not spaced
        self.model, self.letters, self.known = self.tokenizer.model, _byte_letters(), {}
        self.plain = regex.compile(r"[\t\n\r\x20-\x7e\xa1-\xac\xae-\xff]*").fullmatch
        self.cut = regex.compile(SPACED_CUT if spaced else WORD_CUT).findall

    def pieces(self, pieces: list[str]) -> list[list[int]]:
        known, tokenize, letters, plain, cut, out, others = self.known, self.model.tokenize, self.letters, self.plain, self.cut, [], []
        if len(known) > self.limit:
            known.clear()
        lower, first = self.lower, 0 if self.lower else 1  # a spaced piece begins with its space
        for i, piece in enumerate(pieces):
            core = piece[first:] if piece[:first].isspace() else piece
            latin = core.isascii() or max(core) <= "\xff"
            if latin and core.isalpha():
                words = (piece.lower() if lower else piece,)
            elif latin and core[-1:] in ",." and core[:-1].isalpha():
                words = (piece[:-1].lower() if lower else piece[:-1], core[-1])
            elif latin and plain(piece):
                words = cut(piece.lower() if lower else piece)
            else:
                others.append(i)
                out.append(())
                continue
            ids: list[int] = []
            for word in words:
                got = known.get(word)
                if got is None:
                    got = known[word] = tuple([t.id for t in tokenize(word.encode().decode("latin-1").translate(letters))])
                ids += got
            out.append(ids)
        whole = self.tokenizer.encode_batch_fast([pieces[i] for i in others], add_special_tokens=False) if others else []
        for i, found in zip(others, whole):
            out[i] = found.ids
        return out

    def whole(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids


class PieceEncoder:
    """Ids of whole texts.  ``spaced``: whether a piece after a space is encoded with that space (byte-level BPE)."""

    def __init__(self, codec, spaced: bool, room: Room = LARGE):
        self.codec, self.spaced, self.limit, self.slice_bytes = codec, spaced, room.pieces, room.slice_bytes
        self._reset()

    def _reset(self) -> None:
        self.number: dict[str, int] = {}
        self.ids = np.zeros(1 << 16, np.uint32)
        self.first = np.zeros(1 << 15, np.int64)  # where the ids of a piece begin
        self.count = np.zeros(1 << 15, np.int64)
        self.uses = np.zeros(1 << 15, np.int32)  # in how many slices a piece came
        self.used = 0

    def _trim(self) -> None:
        """Forgets what came in one slice alone, and the least used half where that is still too much."""
        n = len(self.number)
        uses = self.uses[:n]
        stay = uses >= max(2, int(np.partition(uses, n - self.limit // 2)[n - self.limit // 2]))
        chosen = np.flatnonzero(stay)[: self.limit // 2]
        size = self.count[chosen]
        ends = np.cumsum(size)
        place = np.repeat(self.first[chosen] - (ends - size), size) + np.arange(ends[-1] if len(ends) else 0)
        pieces, ids, uses = list(self.number), self.ids[place], uses[chosen] // 2
        self._reset()
        self._add([pieces[i] for i in chosen.tolist()], size, ids)
        self.uses[: len(chosen)] = uses

    def _learn(self, pieces: list[str]) -> None:
        ids = self.codec.pieces(pieces)
        sizes = np.fromiter(map(len, ids), np.int64, len(ids))
        self._add(pieces, sizes, np.fromiter(chain.from_iterable(ids), np.uint32, int(sizes.sum())))

    def _add(self, pieces: list[str], sizes: np.ndarray, flat: np.ndarray) -> None:
        n, more = len(self.number), len(pieces)
        while self.used + len(flat) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        while n + more > len(self.first):
            self.first, self.count, self.uses = (np.concatenate([x, np.zeros_like(x)]) for x in (self.first, self.count, self.uses))
        self.ids[self.used : self.used + len(flat)] = flat
        self.first[n : n + more] = self.used + np.cumsum(sizes) - sizes
        self.count[n : n + more] = sizes
        self.used += len(flat)
        self.number.update(zip(pieces, range(n, n + more)))

    def _numbers(self, pieces: list[str]) -> np.ndarray:
        known = self.number
        found = list(map(known.get, pieces))
        if None in found:
            self._learn(list(dict.fromkeys([p for p, x in zip(pieces, found) if x is None])))
            found = list(map(known.__getitem__, pieces))
        return np.array(found, np.int64)

    def piece_numbers(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(numbers of pieces in this encoder, bounds by text) of texts with regular white space."""
        if len(self.number) > self.limit:
            self._trim()
        lists = pc.split_pattern(texts, " ")
        bounds = np.asarray(lists.offsets).astype(np.int64)
        bounds -= bounds[0]
        coded = lists.flatten().dictionary_encode()
        lead = " " if self.spaced else ""
        of_word = self._numbers([lead + w for w in coded.dictionary.to_pylist()])
        self.uses[of_word] += 1  # each number once
        number = of_word[np.asarray(coded.indices)]
        if self.spaced:  # the first piece of a text has no space before it
            words = coded.dictionary.take(coded.indices.take(pa.array(bounds[:-1]))).to_pylist()
            number[bounds[:-1]] = self._numbers(words)
        return number, bounds

    def gather(self, number: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, bounds by text) of pieces."""
        sizes = self.count[number]
        ends = np.cumsum(sizes)
        place = np.repeat(self.first[number] - (ends - sizes), sizes) + np.arange(ends[-1] if len(ends) else 0)
        return self.ids[place], np.concatenate([[0], ends])[bounds]

    def runs(self, texts: pa.Array) -> Iterator[tuple[int, pa.Array, bool]]:
        """(row, texts, whether their white space is regular).  Null counts as empty."""
        for begin, part in byte_slices(pc.fill_null(texts.cast(pa.large_string()), ""), self.slice_bytes):
            irregular = np.asarray(pc.match_substring_regex(part, IRREGULAR))
            edges = np.flatnonzero(np.diff(irregular.astype(np.int8))) + 1
            for a, b in zip([0, *edges], [*edges, len(part)]):
                yield begin + int(a), part.slice(a, b - a), not irregular[a]

    def encode(self, texts: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(row, ids, bounds) of runs of rows: row + i has ids[bounds[i]:bounds[i + 1]]."""
        for row, part, regular in self.runs(texts):
            if regular:
                yield row, *self.gather(*self.piece_numbers(part))
                continue
            for i, text in enumerate(part.to_pylist()):
                ids = np.array(self.codec.whole(text), np.uint32)
                yield row + i, ids, np.array([0, len(ids)])


def library_encoder(path: str, spaced: bool, room: Room = LARGE) -> PieceEncoder:
    """The worker's encoder for a vocabulary file of the ``tokenizers`` library."""
    return worker_state(("library", path, spaced, room), lambda: PieceEncoder(LibraryCodec(path, spaced, room.words), spaced, room))
