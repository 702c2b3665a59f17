"""Byte-level BPE encoding by a lazily determinised transducer, and streaming decoding.

Encoding.  A token sequence is the BPE encoding of its bytes exactly when each token encodes to itself and each pair
of neighbours encodes to that pair.  So the encoding of every prefix ends with one certain token, and reading bytes
from left to right keeps a chain of such tokens.  The transducer's state is the last emitted token and the bytes
after it; a byte leads to the state of the longer bytes, and tokens are emitted as soon as every way to go on passes
through them: a later token can start only where the pending bytes begin some vocabulary entry, which bounds the
look-ahead by the longest entry.  States and moves are made when they are first needed and kept.

Whether two tokens may stand side by side follows from their merges in isolation: both are replayed in the order of
ranks, and the pair fails if a merge across the border would come first at some time.

Decoding.  Ids become bytes; ``StreamDecoder`` hands out whole characters and keeps an unfinished one as the state of
a UTF-8 automaton until the next call.

A null text counts as empty; an empty text has no ids and decodes to nothing.  Rows are treated one by one (repeats,
ties and skew do not matter); extra columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from walkengine.llm.common import only, read_table
from walkengine.llm.vocab import PieceEncoder, worker_state

#: States that a worker keeps; beyond it the transducer starts anew (a matter of memory, not of results).
MAX_STATES = 350_000
#: Ids that the query gives to the streaming decoder at a time.
FEED = 4096
#: Matches whose ids a worker keeps.
MAX_WORDS = 350_000


def load_ranks(path: str) -> dict[bytes, int]:
    """bytes -> id of a file of ranks."""
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


_ROOM = 32
#: Low bits of a packed pair (start, node) or (start, id).
_LOW = (1 << _ROOM) - 1


class MergeTransducer:
    """A state is what the bytes to come can depend on: for each end of the pending bytes the (start, id) that their
    encoding ends with (``chains``), each start from which the pending bytes begin some entry, with its node in the trie
    of entries (``opens``), and the last emitted id where a token may still begin right after it (``befores``).  Pairs
    are packed into one number; moves and states have numbers too, so that a million of them stays small."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks, self.entry = ranks, {i: t for t, i in ranks.items()}
        self.trie: dict[int, int] = {}  # node << 8 | byte -> node; the root is 0
        self.at, self.inner = [-1], [True]  # a node's id (-1: none), and whether longer entries go on from it
        for token, i in ranks.items():
            node = 0
            for byte in token:
                below = self.trie.get(node << 8 | byte)
                if below is None:
                    below = self.trie[node << 8 | byte] = len(self.at)
                    self.at.append(-1)
                    self.inner.append(False)
                self.inner[node] = True
                node = below
            self.at[node] = i
        self.history: dict[int, list[tuple[int, bytes, bytes]] | None] = {}
        self.beside: dict[int, bool] = {}
        self._reset()

    def _reset(self) -> None:
        self.numbers: dict[tuple, int] = {}
        self.befores: list[int] = []
        self.chains: list[tuple[int, ...]] = []
        self.opens: list[tuple[int, ...]] = []
        self.moves: dict[int, int] = {}  # state << 8 | byte -> state, or ~state if ids are emitted
        self.emitted: dict[int, tuple[int, ...]] = {}
        self.start = self._state(-1, (), ())

    def _state(self, before: int, chain: tuple[int, ...], opens: tuple[int, ...]) -> int:
        if chain and (not opens or opens[0] >> _ROOM):
            before = -1  # no token can begin right after it any more
        key = before, chain, opens
        found = self.numbers.get(key)
        if found is None:
            found = self.numbers[key] = len(self.befores)
            self.befores.append(before)
            self.chains.append(chain)
            self.opens.append(opens)
        return found

    def merges(self, token: int) -> list[tuple[int, bytes, bytes]] | None:
        """(rank, left edge, right edge) after each merge of the token's own bytes; None if they don't become it."""
        if token in self.history:
            return self.history[token]
        data = self.entry[token]
        parts, steps = [data[i : i + 1] for i in range(len(data))], []
        while len(parts) > 1:
            rank, i = min(((self.ranks.get(a + b, 1 << 40), i) for i, (a, b) in enumerate(zip(parts, parts[1:]))))
            if rank == 1 << 40:
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            steps.append((rank, parts[0], parts[-1]))
        self.history[token] = found = steps if len(parts) == 1 else None
        return found

    def adjacent(self, left: int, right: int) -> bool:
        """Whether the two tokens encode to themselves and stay apart when their bytes are encoded together."""
        key = left << 32 | right
        if key in self.beside:
            return self.beside[key]
        b = self.merges(right)
        if b is None or left < 0:
            self.beside[key] = b is not None
            return b is not None
        a, i, j = self.merges(left), 0, 0
        edge, lead, never, apart = self.entry[left][-1:], self.entry[right][:1], 1 << 40, True
        while True:
            next_a = a[i][0] if i < len(a) else never
            next_b = b[j][0] if j < len(b) else never
            across = self.ranks.get(edge + lead, never)
            # of equal ranks the leftmost merges first: the left token's, the one across, the right token's
            if across < next_a and across <= next_b and across < never:
                apart = False
                break
            if next_a == never and next_b == never:
                break
            if next_a <= next_b:
                edge, i = a[i][2], i + 1
            else:
                lead, j = b[j][1], j + 1
        self.beside[key] = apart
        return apart

    def _move(self, state: int, byte: int) -> int:
        """The number under which the move is kept, once its ends are known."""
        chain, trie, at, inner, beside = self.chains[state], self.trie, self.at, self.inner, self.beside
        n, opens, last = len(chain), [], -1
        for pair in (*self.opens[state], len(chain) << _ROOM):  # a longer token can only begin where an entry is begun
            edge = (pair & _LOW) << 8 | byte
            if edge not in trie:
                continue
            node = trie[edge]
            start = pair >> _ROOM
            if last < 0 and at[node] >= 0:  # of the tokens that end here the first that fits what is before it
                token = at[node]
                previous = chain[start - 1] & _LOW if start else self.befores[state]
                apart = beside.get(previous << 32 | token)
                if apart if apart is not None else self.adjacent(previous, token):
                    last = start << _ROOM | token
            if inner[node]:
                opens.append(start << _ROOM | node)
        chain = (*chain, last)
        # ends from which one may go on, as bits; the last end that all of them have behind them is certain
        live = 1 << n + 1
        for pair in opens:
            live |= 1 << (pair >> _ROOM)
        while live & (live - 1):
            top = live.bit_length() - 1
            live = live ^ (1 << top) | 1 << (chain[top - 1] >> _ROOM)
        cut, key = live.bit_length() - 1, state << 8 | byte
        if not cut:
            found = self._state(self.befores[state], chain, tuple(opens))
        else:
            out, end = [], cut
            while end:
                pair = chain[end - 1]
                out.append(pair & _LOW)
                end = pair >> _ROOM
            by = cut << _ROOM  # what began before the cut is never gone on from
            kept = tuple([max(pair - by, 0) for pair in chain[cut:]])
            found = ~self._state(chain[cut - 1] & _LOW, kept, tuple([pair - by for pair in opens]))
            self.emitted[key] = tuple(reversed(out))
        self.moves[key] = found
        return found

    def _finish(self, state: int, byte: int) -> list[int]:
        """What is still to be emitted if the piece ends with this byte.  No move is kept: a piece that comes again is
        known as a whole, and most last moves belong to one piece alone."""
        chain, trie, at, beside = self.chains[state], self.trie, self.at, self.beside
        for pair in (*self.opens[state], len(chain) << _ROOM):
            edge = (pair & _LOW) << 8 | byte
            if edge not in trie:
                continue
            token = at[trie[edge]]
            if token < 0:
                continue
            end = pair >> _ROOM
            previous = chain[end - 1] & _LOW if end else self.befores[state]
            apart = beside.get(previous << 32 | token)
            if apart if apart is not None else self.adjacent(previous, token):
                break
        path = [token]
        while end:
            path.append(chain[end - 1] & _LOW)
            end = chain[end - 1] >> _ROOM
        path.reverse()
        return path

    def encode(self, piece: bytes) -> list[int]:
        whole = self.ranks.get(piece)
        if whole is not None and self.merges(whole) is not None:
            return [whole]
        if len(self.befores) > MAX_STATES:
            self._reset()
        if len(self.beside) > 4 * MAX_STATES:
            self.beside.clear()
        if not piece:
            return []
        state, out, moves = self.start, [], self.moves
        for byte in piece[:-1]:
            key = state << 8 | byte
            state = moves[key] if key in moves else self._move(state, byte)
            if state < 0:
                out += self.emitted[key]
                state = ~state
        return out + self._finish(state, piece[-1])


class StreamDecoder:
    """Text from ids that come in parts: the state between two parts is the begin of a character that is not complete.
    Invalid bytes become U+FFFD in text, as ``bytes.decode(errors="replace")`` has it."""

    def __init__(self, vocabulary: list[bytes] | dict[int, bytes]):
        self.vocabulary, self.held = vocabulary, b""

    @staticmethod
    def unfinished(data: bytes) -> int:
        """How many of the last bytes are the valid begin of a character that is not complete."""
        for back in range(1, min(3, len(data)) + 1):
            lead = data[-back]
            if lead & 0xC0 == 0x80:
                continue
            need = 2 if 0xC2 <= lead <= 0xDF else 3 if 0xE0 <= lead <= 0xEF else 4 if 0xF0 <= lead <= 0xF4 else 0
            if back >= need:
                return 0
            if back > 1:  # the second byte has a narrower range after some leads
                low = {0xE0: 0xA0, 0xF0: 0x90}.get(lead, 0x80)
                high = {0xED: 0x9F, 0xF4: 0x8F}.get(lead, 0xBF)
                if not low <= data[1 - back] <= high:
                    return 0
            return back
        return 0

    def feed_bytes(self, ids: Iterable[int]) -> bytes:
        """The bytes of the characters that are complete now."""
        data = self.held + b"".join(map(self.vocabulary.__getitem__, ids))
        keep = self.unfinished(data)
        self.held = data[len(data) - keep :]
        return data[: len(data) - keep] if keep else data

    def close_bytes(self) -> bytes:
        data, self.held = self.held, b""
        return data

    def feed(self, ids: Iterable[int]) -> str:
        return self.feed_bytes(ids).decode("utf-8", "replace")

    def close(self) -> str:
        return self.close_bytes().decode("utf-8", "replace")


class TransducerCodec:
    """Pieces and whole texts: the pattern cuts them, the transducer encodes each match (once while it is kept)."""

    def __init__(self, path: str, pattern: str):
        import regex

        self.ranks = load_ranks(path)
        self.transducer, self.matches = MergeTransducer(self.ranks), regex.compile(pattern).findall
        self.vocabulary = [self.transducer.entry.get(i, b"") for i in range(max(self.transducer.entry, default=-1) + 1)]
        self.decimal = list(map(str, range(len(self.vocabulary))))
        self.known: dict[str, tuple[int, ...]] = {}
        # words are single matches of the public pattern, with or without the space before; other patterns always cut
        self.letters_match = all(self.matches(x) == [x] for x in ("aé", " aé")) and self.matches(" a,") == [" a", ","]

    def _ids(self, match: str) -> tuple[int, ...]:
        found = self.known.get(match)
        if found is None:
            if len(self.known) > MAX_WORDS:
                self.known.clear()
            found = self.known[match] = tuple(self.transducer.encode(match.encode()))
        return found

    def whole(self, text: str) -> list[int]:
        return [i for match in self.matches(text) for i in self._ids(match)]

    def pieces(self, pieces: list[str]) -> list:
        out, letters_match, ids_of, known, whole = [], self.letters_match, self._ids, self.known, self.whole
        for piece in pieces:
            core = piece[1:] if piece[:1] == " " else piece
            if letters_match and core.isalpha() and (core.isascii() or max(core) <= "\xff"):
                out.append(known[piece] if piece in known else ids_of(piece))
            elif letters_match and core[-1:] in ",." and core[:-1].isalpha() and (core.isascii() or max(core) <= "\xff"):
                word = piece[:-1]
                out.append((known[word] if word in known else ids_of(word)) + ids_of(core[-1]))
            else:
                out.append(whole(piece))
        return out


def codec(path: str, pattern: str) -> PieceEncoder:
    return worker_state(("transducer", path, pattern), lambda: PieceEncoder(TransducerCodec(path, pattern), spaced=True))


def encode_texts(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id and the ids of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = codec(path, pattern)
        for batch in batches:
            for row, ids, bounds in encoder.encode(batch["text"]):
                lists = pa.ListArray.from_arrays(pa.array(bounds.astype("int32")), pa.array(ids.astype("int32")))
                yield pa.RecordBatch.from_arrays([batch["doc_id"].slice(row, len(lists)).cast(pa.int64()), lists], names=["doc_id", "ids"])

    return only(docs, "doc_id", "text").mapInArrow(run, "doc_id long, ids array<int>")


def decode_ids(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id and the text of every list of ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = worker_state(("vocabulary", path), lambda: {i: t for t, i in load_ranks(path).items()})
        for batch in batches:
            texts = []
            for ids in batch["ids"]:
                stream = StreamDecoder(vocabulary)
                texts.append(stream.feed(ids.as_py() or []) + stream.close())
            yield pa.RecordBatch.from_arrays([batch["doc_id"].cast(pa.int64()), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return only(encoded, "doc_id", "ids").mapInArrow(run, "doc_id long, text string")


DIGEST = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])


def round_trip_digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of every text, in the scan and without a shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = codec(path, pattern)
        stream = StreamDecoder(encoder.codec.vocabulary)

        def decoded(ids: list[int]) -> str:
            digest = hashlib.sha256()
            for a in range(0, len(ids), FEED):
                digest.update(stream.feed_bytes(ids[a : a + FEED]))
            digest.update(stream.close_bytes())
            return digest.hexdigest()

        decimal = encoder.codec.decimal.__getitem__
        for batch in batches:
            for row, ids, bounds in encoder.encode(batch["text"]):
                ids, rows = ids.tolist(), []
                for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                    own = ids[a:b]
                    rows.append((b - a, hashlib.sha256(",".join(map(decimal, own)).encode()).hexdigest(), decoded(own)))
                columns = [pa.array(c, t) for c, t in zip(zip(*rows), DIGEST.types[1:])]
                yield pa.RecordBatch.from_arrays([batch["doc_id"].slice(row, len(rows)).cast(pa.int64()), *columns], schema=DIGEST)

    return only(docs, "doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op5_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as public

    return round_trip_digests(read_table(spark, sf_dir, "documents"), public.path("byte_bpe_multi_50k.tiktoken"), public.PATTERN)


QUERIES = {"op5_bpe_codec": op5_bpe_codec}
ORACLES: dict[str, str] = {}
