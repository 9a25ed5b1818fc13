"""Byte-level BPE as a lazily determinised finite-state transducer, with a streaming decoder.

Reading a piece byte by byte, the last token of the encoding of each prefix is unique: it is the one token
ending there that BPE keeps apart from the last token before it.  A state therefore needs only the longest
suffix of the input that can still grow into a token, and the last tokens at the places inside that suffix
where a longer token may start.  States and their transitions are made when first met.  A token leaves as
soon as all continuations share it."""

from __future__ import annotations

import base64
import hashlib
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame

from .common import arrow_map, column, slices, tidy

START = -1


def load_ranks(data: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in (line.split() for line in data.splitlines() if line)}


class State(dict):
    """Next states by byte.  ``token`` is the last token here, ``lasts`` the last tokens at the open places of
    ``suffix``, ending with ``token``; a passing state is not kept and no state leads to it for good."""

    __slots__ = ("fst", "suffix", "lasts", "token", "passing")

    def __init__(self, fst: Transducer, suffix: bytes, lasts: tuple[int, ...], passing: bool = False):
        self.fst, self.suffix, self.lasts, self.token, self.passing = fst, suffix, lasts, lasts[-1], passing

    def __missing__(self, byte: int) -> State:
        to = self.fst.step(self, byte)
        if not (to.passing or self.passing):
            self[byte] = to
        return to


class Transducer:
    """encode(piece) gives token ids.  At most ``most_states`` states are kept; beyond that states are passing,
    and after ``renew`` passing states for each one kept (the text has changed) it starts afresh."""

    def __init__(self, ranks: dict[bytes, int], most_states: int = 150_000, flush_every: int = 512, renew: int = 50):
        self.ranks, self.most_states, self.flush_every, self.renew = ranks, most_states, flush_every, renew
        self.vocabulary = max(ranks.values(), default=-1) + 1
        self.bytes_of = [b""] * self.vocabulary
        for token, i in ranks.items():
            self.bytes_of[i] = token
        self.sizes = [len(t) for t in self.bytes_of]
        self.prefixes = {t[:n] for t in ranks for n in range(1, len(t))}
        self.apart: dict[int, bool] = {}
        self.halves: dict[int, tuple[int, int] | None] = {}
        self.wholes: dict[int, bool] = {}
        self.single = [bytes([b]) for b in range(256)]
        self.states: dict[tuple, State] = {}
        self._reset()

    def _reset(self) -> None:
        for state in self.states.values():  # they hold one another
            state.clear()
        self.start = State(self, b"", (START,))
        self.states = {(b"", (START,)): self.start}
        self.shapes: dict[bytes, tuple] = {}
        self.passed = 0

    def merge(self, piece: bytes, until: int = 1) -> list[int]:
        """The rank rule itself, for short strings: join the pair of lowest rank, leftmost first."""
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while len(parts) > until:
            best, at = min(((self.ranks.get(a + b, 1 << 60), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False))))
            if best == 1 << 60:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [self.ranks[p] for p in parts]

    def _halves(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose join made this one; None for a single byte."""
        if (known := self.halves.get(token, 0)) == 0:
            parts = [self.bytes_of[token]]
            if len(parts[0]) > 1:
                parts = self.merge(parts[0], until=2)
            known = self.halves[token] = (parts[0], parts[1]) if len(parts) == 2 else None
        return known

    def _keeps(self, left: int, right: int) -> bool:
        """Whether BPE leaves the two tokens apart when they stand side by side.

        Runs time backwards: undoes the join of higher rank on either side of the border and asks at each
        moment whether the two parts at the border would have joined before either was used up (of equal
        ranks the one further left goes first)."""
        ranks, bytes_of, never = self.ranks, self.bytes_of, 1 << 60
        left_used = right_used = never
        while True:
            joined = ranks.get(bytes_of[left] + bytes_of[right], never)
            if joined < left_used and joined <= right_used and joined != never:
                return False
            one, two = self._halves(left), self._halves(right)
            if one is not None and (two is None or left > right):
                left_used, left = left, one[1]
            elif two is not None:
                right_used, right = right, two[0]
            else:
                return True

    def _shape(self, grown: bytes) -> tuple:
        """What depends on the bytes of a state and the next byte only: tokens that may end here, longest first,
        each with the open place where it starts; the next suffix; which open places stay open."""
        size, prefixes = len(grown), self.prefixes
        was = [j for j in range(size) if j == size - 1 or grown[j:-1] in prefixes]
        ends = []
        for place, j in enumerate(was):
            t = self.ranks.get(grown[j:])
            if t is not None and (j == size - 1 or self._whole(t)):
                ends.append((place, t))
        stay = [place for place, j in enumerate(was) if grown[j:] in prefixes]
        return ends, grown[was[stay[0]] :] if stay else b"", stay

    def step(self, state: State, byte: int) -> State:
        """The state after one more byte."""
        grown = state.suffix + self.single[byte]
        if (shape := self.shapes.get(grown)) is None:
            shape = self.shapes[grown] = self._shape(grown)
        ends, suffix, stay = shape
        lasts, apart = state.lasts, self.apart
        for place, token in ends:
            left = lasts[place]
            if left == START:
                break
            key = left * self.vocabulary + token
            if (known := apart.get(key)) is None:
                if len(apart) > 4 * self.most_states:
                    apart.clear()
                known = apart[key] = self._keeps(left, token)
            if known:
                break
        else:
            raise ValueError("a byte without a token")
        now = (*[lasts[i] for i in stay], token)
        if (to := self.states.get((suffix, now))) is None:
            if len(self.states) >= self.most_states:
                self.passed += 1
                return State(self, suffix, now, passing=True)
            to = self.states[suffix, now] = State(self, suffix, now)
        return to

    def _whole(self, token: int) -> bool:
        """Whether BPE makes this token of its own bytes."""
        if (known := self.wholes.get(token)) is None:
            known = self.wholes[token] = self.merge(self.bytes_of[token]) == [token]
        return known

    def stream(self, piece: bytes):
        """Token ids of one piece in order, with bounded lookahead and memory."""
        for part in self._runs(piece):
            yield from part

    def _runs(self, piece: bytes):
        if self.passed > self.renew * self.most_states:
            self._reset()
        state, last = self.start, [START]  # last[i]: the token that ends i bytes after what has left
        for start in range(0, len(piece), self.flush_every):
            for byte in piece[start : start + self.flush_every]:
                state = state[byte]
                last.append(state.token)
            if start + self.flush_every < len(piece) and (common := self._common(len(last) - 1, len(state.suffix), last)):
                yield self._chain(last, common)
                last = last[common:]
        yield self._chain(last, len(last) - 1)

    def _chain(self, last: list[int], end: int) -> list[int]:
        out, sizes = [], self.sizes
        while end > 0:
            out.append(token := last[end])
            end -= sizes[token]
        out.reverse()
        return out

    def _common(self, here: int, open_: int, last: list[int]) -> int:
        """The furthest place that the encodings of all continuations pass through."""
        sizes = self.sizes
        line, i = set(), here
        while i > 0:
            line.add(i)
            i -= sizes[last[i]]
        line.add(0)
        meet = here
        for i in range(here - open_, here + 1):
            while i > 0 and i not in line:
                i -= sizes[last[i]]
            meet = min(meet, max(i, 0))
        return meet

    def encode(self, piece: bytes) -> tuple[int, ...]:
        known = self.ranks.get(piece)  # a piece that is a token is that token
        if known is not None:
            return (known,)
        if len(piece) > self.flush_every:
            return tuple(chain.from_iterable(self._runs(piece)))
        if self.passed > self.renew * self.most_states:
            self._reset()
        state, last = self.start, [START]
        for byte in piece:
            state = state[byte]
            last.append(state.token)
        return tuple(self._chain(last, len(piece)))


class Utf8Stream:
    """Incremental UTF-8: feed() returns the text that is complete; bytes that can't be right become U+FFFD."""

    def __init__(self):
        self.held = b""

    def feed(self, data: bytes, end: bool = False) -> str:
        data = self.held + data
        cut = len(data) if end else len(data) - self._open(data)
        self.held = data[cut:]
        return data[:cut].decode("utf-8", "replace")

    @staticmethod
    def _open(data: bytes) -> int:
        """How many bytes at the end can be the start of a longer character."""
        for back in range(1, min(3, len(data)) + 1):
            lead = data[-back]
            if lead & 0xC0 != 0x80:
                need = 2 if 0xC2 <= lead <= 0xDF else 3 if 0xE0 <= lead <= 0xEF else 4 if 0xF0 <= lead <= 0xF4 else 1
                if need <= back:
                    return 0
                if back >= 2:
                    low, high = {0xE0: (0xA0, 0xBF), 0xED: (0x80, 0x9F), 0xF0: (0x90, 0xBF), 0xF4: (0x80, 0x8F)}.get(lead, (0x80, 0xBF))
                    if not low <= data[-back + 1] <= high:
                        return 0
                return back
        return 0


class Pieces(dict):
    """Ids of pieces met before, as text with a character for each id; a new piece is encoded when looked up.

    Holds up to ``memory`` pieces in two generations: when the young one is full the old one goes, except for
    the pieces that are met again meanwhile."""

    def __init__(self, fst: Transducer, memory: int):
        self.fst, self.half, self.old = fst, max(1, memory // 2), {}

    def __missing__(self, piece: str) -> str:
        ids = self.old.get(piece)
        if ids is None:
            ids = "".join(map(chr, self.fst.encode(piece.encode())))
        if len(piece) <= 64:
            if len(self) >= self.half:
                self.old = dict(self)
                self.clear()
            self[piece] = ids
        return ids


class Codec:
    """Splits a text by the pattern, encodes each match and decodes ids; remembers up to ``memory`` pieces."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, memory: int = 400_000, most_states: int = 100_000):
        import regex

        self.fst = Transducer(ranks, most_states)
        if self.fst.vocabulary > 0x110000:
            raise ValueError("ids beyond 1,114,111 don't fit a character each")
        self.known = Pieces(self.fst, memory)
        self.pieces = regex.compile(pattern).findall
        self.bytes_of = pa.array(self.fst.bytes_of, pa.binary())

    def encode(self, text: str) -> list[int]:
        return self.numbers(text).tolist()

    def numbers(self, text: str) -> np.ndarray:
        """Ids as unsigned 32-bit numbers."""
        ids = "".join(map(self.known.__getitem__, self.pieces(text)))
        return np.frombuffer(ids.encode("utf-32-le", "surrogatepass"), np.uint32)

    def decode(self, ids, chunk: int = 1 << 16):
        """Yields (bytes, complete text) by chunks."""
        utf8, ids = Utf8Stream(), np.asarray(ids, np.uint32)
        for i in range(0, len(ids), chunk):
            data = self._joined(ids[i : i + chunk])
            yield data, utf8.feed(data)
        if utf8.held:
            yield b"", utf8.feed(b"", end=True)

    def _joined(self, ids: np.ndarray) -> bytes:
        """Bytes of the tokens one after the other: the value buffer of a freshly gathered column."""
        parts = self.bytes_of.take(pa.array(ids))
        ends = np.frombuffer(parts.buffers()[1], np.int32, len(parts) + 1, parts.offset * 4)
        return parts.buffers()[2].slice(int(ends[0]), int(ends[-1] - ends[0])).to_pybytes() if len(parts) else b""

    def checked(self, text: str, ids: np.ndarray):
        """Bytes of the ids by chunks; an error at the end if they are not the text."""
        at = 0
        for data, part in self.decode(ids):
            if not text.startswith(part, at):
                raise ValueError("ids do not decode to the text they were made of")
            at += len(part)
            yield data
        if at != len(text):
            raise ValueError("ids do not decode to the text they were made of")


_KEPT: dict[tuple, Codec] = {}


def _codec(docs: DataFrame, path: str, pattern: str, **bounds: int):
    """The rank file has a fixed size (under 1 MB), so it is broadcast.  A Python worker compiles it once and
    keeps one codec with what it remembers for its next tasks, within the bounds."""
    with open(path, "rb") as f:
        shared = docs.sparkSession.sparkContext.broadcast(f.read())

    def get() -> Codec:
        key = (xxhash.xxh3_128_digest(shared.value), pattern, *sorted(bounds.items()))
        if key not in _KEPT:
            _KEPT.clear()
            _KEPT[key] = Codec(load_ranks(shared.value), pattern, **bounds)
        return _KEPT[key]

    return get


def encode(docs: DataFrame, path: str, pattern: str, memory: int = 200_000, most_states: int = 80_000) -> DataFrame:
    """All columns of docs and ``tokens`` (array of ids), which are decoded again and compared with the text.

    A null or empty text has no tokens.  Repeated rows stay and are encoded alike, the order of rows is that of
    docs, an empty table gives an empty one, a column ``tokens`` of docs is replaced.
    memory, most_states: pieces and states that a worker remembers; they bound its memory and change no result."""
    codec, at = _codec(docs, path, pattern, memory=memory, most_states=most_states), docs.columns.index("text")
    from pyspark.sql import types as T

    schema = T.StructType([f for f in docs.schema if f.name != "tokens"] + [T.StructField("tokens", T.ArrayType(T.IntegerType()))])

    def run(batches):
        own = codec()
        for batch in (part for whole in batches for part in slices(whole, at)):
            parts = []
            for text in batch.column(at).to_pylist():
                parts.append(ids := own.numbers(text or ""))
                for _ in own.checked(text or "", ids):
                    pass
            ends = pa.array(np.cumsum([0, *map(len, parts)]), pa.int32())
            kept = [i for i, n in enumerate(batch.schema.names) if n != "tokens"]
            tokens = pa.ListArray.from_arrays(ends, pa.array(np.concatenate([np.zeros(0, np.uint32), *parts]).astype(np.int32)))
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in kept), tokens], names=[*(batch.schema.names[i] for i in kept), "tokens"])

    return docs.mapInArrow(tidy(run), schema)


def decode(frame: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id and the text that ``tokens`` stand for (null tokens: empty).  Bytes that are no UTF-8 become
    U+FFFD; repeated rows stay; other columns are ignored; an empty table gives an empty one."""
    codec = _codec(frame, path, pattern)

    def make():
        own = codec()

        def step(batch):
            out = ["".join(t for _, t in own.decode(ids or [])) for ids in column(batch, "tokens").to_pylist()]
            return {"doc_id": column(batch, "doc_id"), "text": pa.array(out, pa.string())}

        return step

    base = frame.select(frame["doc_id"].cast("long").alias("doc_id"), "tokens")
    return arrow_map(base, make, "doc_id long, text string")


def report(docs: DataFrame, path: str, pattern: str, memory: int = 400_000, most_states: int = 150_000) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 for every row; null texts count as empty.

    Digests are of the ids as decimals joined by a space, and of the bytes the ids decode to, which the streaming
    decoder compares with the text.  Repeated rows and null doc_ids stay as they are; other columns are ignored;
    an empty table gives an empty one.  memory, most_states: as for encode."""
    codec = _codec(docs, path, pattern, memory=memory, most_states=most_states)

    def make():
        own = codec()
        names = [str(i) for i in range(own.fst.vocabulary)]

        def step(batch):
            n, ids_sha, decoded = [], [], []
            for text in column(batch, "text").to_pylist():
                ids = own.numbers(text or "")
                n.append(len(ids))
                ids_sha.append(hashlib.sha256(" ".join(map(names.__getitem__, ids.tolist())).encode()).hexdigest())
                sha = hashlib.sha256()
                for data in own.checked(text or "", ids):
                    sha.update(data)
                decoded.append(sha.hexdigest())
            return {"doc_id": column(batch, "doc_id"), "n_tokens": pa.array(n, pa.int64()), "ids_sha256": pa.array(ids_sha), "decoded_sha256": pa.array(decoded)}

        return step

    base = docs.select(docs["doc_id"].cast("long").alias("doc_id"), "text")
    return arrow_map(base, make, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", slice_by="text")
