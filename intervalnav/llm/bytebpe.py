"""Byte-level BPE by a lazily determinised transducer, and decoding by an incremental UTF-8 machine.

The merges are compiled on demand. Reading a byte string from the left, every prefix has exactly one last
token (the one whose pair with the last token of the shorter prefix is stable under the merges). A state of
the transducer holds what can still matter: the last token that is settled and the bytes after it. A token is
emitted once every continuation agrees on it, that is, once all positions at which a vocabulary token may
still begin share it; the wait is bounded by the longest token. States, transitions and stable pairs are
made when first met and forgotten when there are too many.

Defined cases: a null text counts as empty and has no tokens; rows are coded one by one, so repeated rows
repeat their result; texts of any length are coded whole; special tokens are ordinary text.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import arrowtext as at

STATES = 250_000
PAIRS = 500_000
PIECES = 200_000  # in each of two generations


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


class Transducer:
    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.bytes_of = {i: t for t, i in ranks.items()}
        self.longest = max(map(len, ranks))
        self.beginnings = {t[:n] for t in ranks for n in range(1, len(t))}
        self.stable: dict[tuple[int, int], bool] = {}
        self.reset()

    def reset(self) -> None:
        self.number: dict[tuple, int] = {}
        self.steps: dict[int, tuple[int, tuple[int, ...]]] = {}  # by state * 256 + byte
        self.chains: list[list[tuple[int, int]]] = []  # for each position of the tail: where its last token begins, and the token
        self.keys: list[tuple[int, bytes]] = []
        self._state(-1, b"", [])

    def _state(self, before: int, tail: bytes, chain: list[tuple[int, int]]) -> int:
        key = (before, tail, tuple(chain))
        if (got := self.number.get(key)) is None:
            got = self.number[key] = len(self.keys)
            self.chains.append(chain)
            self.keys.append((before, tail))
        return got

    def merged(self, data: bytes) -> list[int]:
        """Plain merging by rank; used on single pairs only."""
        parts = [data[i : i + 1] for i in range(len(data))]
        rank_of = self.ranks.get
        ranks = [rank_of(a + b, 1 << 60) for a, b in zip(parts, parts[1:], strict=False)]
        while ranks and (least := min(ranks)) < 1 << 60:
            i = ranks.index(least)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del ranks[i]
            if i:
                ranks[i - 1] = rank_of(parts[i - 1] + parts[i], 1 << 60)
            if i < len(ranks):
                ranks[i] = rank_of(parts[i] + parts[i + 1], 1 << 60)
        return [self.ranks[p] for p in parts]

    def is_stable(self, left: int, right: int) -> bool:
        """Whether merging leaves the two tokens as they are; left -1: the beginning of the string."""
        key = (left, right)
        if (got := self.stable.get(key)) is None:
            if len(self.stable) > PAIRS:
                self.stable.clear()
            first = b"" if left < 0 else self.bytes_of[left]
            got = self.stable[key] = self.merged(first + self.bytes_of[right]) == ([right] if left < 0 else [left, right])
        return got

    def _step(self, state: int, byte: int) -> tuple[int, tuple[int, ...]]:
        before, tail = self.keys[state]
        tail += bytes((byte,))
        n, chain, ranks, beginnings = len(tail), self.chains[state], self.ranks, self.beginnings
        found = -1
        live = [n]
        for start in range(max(0, n - self.longest), n):
            part = tail[start:]
            if part in beginnings:
                live.append(start)
            if found < 0:
                token = ranks.get(part)
                if token is not None and self.is_stable(chain[start - 1][1] if start else before, token):
                    found, last = start, token
        if found < 0:
            raise ValueError("the ranks leave a byte without a token")
        chain = [*chain, (found, last)]
        # What all positions where a token may still begin have in common is settled.
        cut = min(live)
        ways = set(live)
        while len(ways) > 1:
            end = max(ways)
            ways.discard(end)
            ways.add(chain[end - 1][0])
            cut = min(ways)
        out = self._walk(chain, cut)
        if cut:
            before, tail, chain = out[-1], tail[cut:], [(s - cut, t) for s, t in chain[cut:]]
        if cut not in live:  # no token can begin there any more, so what stands before it is of no matter
            before = -2
        made = self._state(before, tail, chain), tuple(out)
        self.steps[state << 8 | byte] = made
        return made

    @staticmethod
    def _walk(chain: list[tuple[int, int]], end: int) -> list[int]:
        out: list[int] = []
        while end:
            end, token = chain[end - 1]
            out.append(token)
        return out[::-1]

    def encode(self, data: bytes) -> list[int]:
        whole = self.ranks.get(data)
        if whole is not None:
            return [whole]
        if len(self.keys) > STATES:
            self.reset()
        out: list[int] = []
        state, steps = 0, self.steps
        for byte in data:
            state, more = steps.get(state << 8 | byte) or self._step(state, byte)
            if more:
                out += more
        return out + self._walk(self.chains[state], len(self.chains[state]))


class Utf8Machine:
    """Incremental decoder: ``feed`` gives the characters completed so far, a cut one waits for its rest.

    Ill-formed bytes give U+FFFD for each maximal part, as Unicode recommends.
    """

    def __init__(self, state: tuple[int, int, int, int] = (0, 0x80, 0xBF, 0)):
        self.need, self.low, self.high, self.value = state

    def state(self) -> tuple[int, int, int, int]:
        return self.need, self.low, self.high, self.value if self.need else 0

    def feed(self, data: bytes) -> str:
        out: list[str] = []
        for b in data:
            if self.need:
                if self.low <= b <= self.high:
                    self.value = self.value << 6 | b & 0x3F
                    self.need, self.low, self.high = self.need - 1, 0x80, 0xBF
                    if not self.need:
                        out.append(chr(self.value))
                    continue
                out.append("�")
                self.need, self.low, self.high = 0, 0x80, 0xBF
            if b < 0x80:
                out.append(chr(b))
            elif 0xC2 <= b <= 0xF4:
                self.need = 1 + (b >= 0xE0) + (b >= 0xF0)
                self.value = b & (0x3F >> self.need)
                # Second bytes are limited after these: no overlong forms, surrogates or code points over 10FFFF.
                self.low = {0xE0: 0xA0, 0xF0: 0x90}.get(b, 0x80)
                self.high = {0xED: 0x9F, 0xF4: 0x8F}.get(b, 0xBF)
            else:
                out.append("�")
        return "".join(out)

    def finish(self) -> str:
        out = "�" if self.need else ""
        self.need, self.low, self.high = 0, 0x80, 0xBF
        return out


class Coder:
    """Encoding and decoding of texts, with a bounded memory of pieces already coded."""

    def __init__(self, path: str, pattern: str):
        self.transducer = Transducer(load_ranks(path))
        self.pieces = regex.compile(pattern)
        self.known: dict[str, str] = {}
        self.old: dict[str, str] = {}
        self.moves: dict[tuple, dict] = {}  # of the UTF-8 machine, by state: decimal id to characters and the next moves; "" to the state

    def encode(self, text: str) -> str:
        """Decimal ids joined by spaces."""
        found = self.pieces.findall(text)
        known = self.known
        try:
            return " ".join([known[p] for p in found])
        except KeyError:
            pass
        if len(known) > PIECES:
            self.old, self.known = known, {}
            known = self.known
        for piece in found:
            if piece not in known:
                known[piece] = self.old.get(piece) or " ".join(map(str, self.transducer.encode(piece.encode())))
        return " ".join([known[p] for p in found])

    def _moves(self, state: tuple) -> dict:
        return self.moves.setdefault(state, {"": state})

    def _move(self, moves: dict, token: str) -> tuple[str, dict]:
        machine = Utf8Machine(moves[""])
        text = machine.feed(self.transducer.bytes_of[int(token)])
        moves[token] = made = text, self._moves(machine.state())
        return made

    def decode(self, ids: Iterable[str]) -> Iterator[str]:
        """Characters of the decimal ids, in a stream; what the machine does with a token in a state is done once."""
        if sum(map(len, self.moves.values())) > STATES:
            self.moves.clear()
        moves = self._moves(Utf8Machine().state())
        for i in ids:
            text, moves = moves.get(i) or self._move(moves, i)
            yield text
        yield Utf8Machine(moves[""]).finish()

    def decode_all(self, joined: str) -> str:
        return "".join(self.decode(joined.split(" ") if joined else []))


_coders: dict[tuple[str, str], Coder] = {}


def coder(path: str, pattern: str) -> Coder:
    if (path, pattern) not in _coders:
        _coders[path, pattern] = Coder(path, pattern)
    return _coders[path, pattern]


def code(docs: DataFrame, path: str, pattern: str, key: str = "doc_id", text: str = "text", with_ids: bool = False) -> DataFrame:
    """n_tokens, ids_sha256 and decoded_sha256 of every row; with_ids adds ids (array of int) and decoded (string)."""
    source = docs.select(F.col(key).alias("doc_id"), F.col(text).alias("t"))
    fields = f"doc_id {source.schema['doc_id'].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = coder(path, pattern)
        for batch in batches:
            for part in at.blocks(batch, "t"):
                out: list[list] = [[], [], [], [], []]
                for text in part.column("t").to_pylist():
                    joined = own.encode(text or "")
                    decoded = own.decode_all(joined)
                    row = (joined.count(" ") + 1 if joined else 0, hashlib.sha256(joined.encode()).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest())
                    if with_ids:
                        row += ([int(i) for i in joined.split()], decoded)
                    for column, x in zip(out, row, strict=False):
                        column.append(x)
                types = (pa.int64(), pa.string(), pa.string(), pa.list_(pa.int32()), pa.string())[: 5 if with_ids else 3]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "ids", "decoded"][: 6 if with_ids else 4]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *(pa.array(c, t) for c, t in zip(out, types, strict=False))], names=names)

    return source.mapInArrow(run, fields)
