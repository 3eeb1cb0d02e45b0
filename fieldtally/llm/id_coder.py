"""Token ids in a compressed file format: an adaptive context-mixing range coder over blocks.

Every block of BLOCK ids is reset, coded and checksummed on its own: nothing but its own bytes is needed
to decode it, so a reader can start at any block.  All blocks of a shard are coded in lockstep as the lanes of
numpy arrays.

In a block, orders 2 and 1 each guess one id: what last followed the two ids before, or the id before, and how
often in a row that was right.  Order 0 has the last id of each of 2^RECENT hashes.  Which order holds the id (2, 1,
0, or none: a new id) is a symbol of four whose distribution mixes two adaptive ones, one chosen by how
sure the orders are and one by which were right at the last two ids; the one that did better lately weighs three
quarters.  An id of order 0 is coded by its hash, a new one as it is.  Both symbols together are one
step of a range coder of 64 bits with 32-bit output and carries.  What a block has taught is taken up at the ends
of slices (:func:`slices`) and forgotten at the block's end.  Integers decide everything, so any machine decodes what another wrote.

A file (one for each shard): magic, version, number of ids, of blocks, block length; for each block its number of
ids, its bytes and the CRC-32 of its ids as little-endian 32-bit integers; then the blocks' bytes.  Files are rows of a
table in the shared folder, next to the doc ids and lengths they hold.

Texts are encoded by the tokenizers library, special tokens in them as the library takes them.

Edge cases: a null or empty text is the end id alone; ids must be below 65,535 (``ValueError``
otherwise); a damaged block raises ``ValueError``; rows with the same doc_id follow each other, ordered by
text, and a null doc_id comes first; extra columns are ignored.  An empty table gives an empty table.
"""

from __future__ import annotations

import functools
import itertools
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import buckets_for, drop_suffix, env_single_thread, read_documents, scratch, ship, text_bytes

MAGIC, VERSION = b"FTID", 3
BLOCK = 8192
LANES = 1152
END_ID = 2
NO_ID = 0xFFFF
PAYLOAD = 16  # bits of the second symbol
SLICE, RECENT = 128, 9
_SLOTS = 9  # bits of a block's table of one order
_PARTITION_BYTES = 24 << 20
_CACHE_LIMIT = 600_000
_GROUP_BYTES = 8 << 20

_U0, _U1, _U2, _U4, _U16, _U32, _U48 = (np.uint64(i) for i in (0, 1, 2, 4, 16, 32, 48))
_BITS, _TOTAL = np.uint64(PAYLOAD), np.uint64(14 + PAYLOAD)
#: Bits of the share of 2^PAYLOAD that each symbol of four leaves to the second one's value.
_SPARE, _U_SPARE, _WIDTHS = np.uint32(PAYLOAD - RECENT), np.uint64(PAYLOAD - RECENT), np.array([PAYLOAD, PAYLOAD, PAYLOAD - RECENT, 0], np.uint64)
_LEFT = np.array([((1 << PAYLOAD) - 1) >> int(w) << int(w) for w in _WIDTHS], np.uint64)
_U2_32, _FIELD, _MASK = np.uint64(1 << 32), np.uint64(0xFFFF), np.uint64((1 << 14 + PAYLOAD) - 1)
#: The same value in each of the four 16-bit fields.
_ONES = np.uint64(0x0001000100010001)
_FULL = np.uint64(1 << 14)
_HALVES, _QUARTERS = (np.uint64(0xFFFF >> i) * _ONES for i in (1, 2))
_SPREAD, _SHIFT, _RARE, _NO_ID, _SUREST, _HIGH = (np.uint32(i) for i in (0x9E3779B1, 32 - _SLOTS, 32 - RECENT, NO_ID, 3, 16))


def slices(steps: int) -> list[tuple[int, int]]:
    """(start, end) of a block's slices: short ones first."""
    early = itertools.takewhile(lambda t: t < min(SLICE, steps), (16 << i for i in itertools.count()))
    return list(itertools.pairwise([0, *early, *range(SLICE, steps, SLICE), steps]))


def _packed(counts: np.ndarray) -> np.ndarray:
    """Counts of four symbols as one integer of four 16-bit frequencies, 64 at least, that sum to 2^14."""
    share = 64 + counts * ((1 << 14) - 256) // counts.sum(1, keepdims=True)
    share[:, 3] += (1 << 14) - share.sum(1)
    return (share.astype(np.uint64) << (np.arange(4, dtype=np.uint64) << _U4)).sum(1, dtype=np.uint64)


def _hashed(context: np.ndarray) -> np.ndarray:
    return context * _SPREAD >> _SHIFT


class _Lanes:
    """What n independent blocks have taught so far; the rows of arrays are lanes."""

    def __init__(self, n: int):
        #: for each lane and hashed context an id and, above its 16 bits, how sure it is (0: none yet, to 3)
        self.two, self.one = (np.full(n << _SLOTS, NO_ID, np.uint32) for _ in range(2))
        self.zero, self.recent = np.full(n << RECENT, NO_ID, np.uint16), np.arange(n, dtype=np.uint32) << RECENT
        self.base, self.lane = np.arange(n, dtype=np.uint32) << _SLOTS, np.arange(n, dtype=np.int64) << 4
        self.counts = [np.ones((n * 16, 4), np.int64) for _ in range(2)]
        self.sure, self.past = (_packed(c) for c in self.counts)
        self.score, self.better = np.zeros(n, np.int64), np.ones(n, bool)
        self.before, self.earlier = (np.zeros(n, np.uint32) for _ in range(2))
        self.history = np.zeros(n, np.int64)

    def places(self, before: np.ndarray, earlier: np.ndarray, base: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return _hashed(before << _HIGH | earlier) + base, _hashed(before) + base

    def mixed(self, a: np.ndarray, b: np.ndarray, better: np.ndarray) -> np.ndarray:
        out = ((a >> _U2) & _QUARTERS) + ((b >> _U2) & _QUARTERS) + ((np.where(better, a, b) >> _U1) & _HALVES)
        # What flooring took goes to the fourth symbol.
        return out + ((_FULL - (out * _ONES >> _U48)) << _U48)

    def judged(self, now: np.ndarray, flag: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray | None, np.ndarray]:
        """(flag, distribution, hash) of a slice of ids, which is then learnt.  flag: if it is known already; there is no distribution then."""
        before = np.concatenate([self.before[:, None], now[:, :-1]], 1)
        earlier = np.concatenate([self.earlier[:, None], before[:, :-1]], 1)
        at_two, at_one = self.places(before, earlier, self.base[:, None])
        two, one = self.two.take(at_two), self.one.take(at_one)
        right_two, right_one = (two & _NO_ID) == now, (one & _NO_ID) == now
        slot = now * _SPREAD >> _RARE
        at_zero = slot + self.recent[:, None]
        if coding := flag is None:
            flag = np.where(right_two, 0, np.where(right_one, 1, np.where(self.zero.take(at_zero) == now, 2, 3)))
        self.zero[at_zero.ravel()] = now.ravel()
        sure_two, sure_one = two >> _HIGH, one >> _HIGH
        row_a = (sure_two << 2 | sure_one) + self.lane[:, None]
        last = np.concatenate([self.history[:, None] & 3, flag[:, :-1]], 1)
        row_b = (np.concatenate([self.history[:, None] >> 2, last[:, :-1]], 1) << 2 | last) + self.lane[:, None]
        a, b = self.sure.take(row_a), self.past.take(row_b)
        out = self.mixed(a, b, self.better[:, None]) if coding else None
        at = flag.astype(np.uint64) << _U4
        gain = ((a >> at) & _FIELD).astype(np.int64) - ((b >> at) & _FIELD).astype(np.int64)
        self.score += gain.sum(1) - (self.score >> 1)
        self.better = self.score >= 0
        for table, place, sure, right in ((self.two, at_two, sure_two, right_two), (self.one, at_one, sure_one, right_one)):
            # Of a place that occurs twice the last entry stays.
            table[place.ravel()] = (np.minimum(sure * right + np.uint32(1), _SUREST) << _HIGH | now).ravel()
        for counts, row in zip(self.counts, (row_a, row_b), strict=True):
            counts += 4 * np.bincount((row << 2 | flag).ravel(), minlength=counts.size).reshape(counts.shape)
            counts[counts.sum(1) > 4096] >>= 1
            counts += counts == 0
        self.sure, self.past = (_packed(c) for c in self.counts)
        ends = np.concatenate([self.earlier[:, None], self.before[:, None], now], 1)
        self.earlier, self.before = ends[:, -2].copy(), ends[:, -1].copy()
        self.history = (np.concatenate([self.history[:, None] & 3, flag], 1)[:, -2] << 2) | flag[:, -1]
        return flag, out, slot


def _span(packed: np.ndarray, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(cumulative, frequency) of each lane's symbol."""
    at = symbol.astype(np.uint64) << _U4
    frequency = (packed >> at) & _FIELD
    return ((packed * _ONES >> at) & _FIELD) - frequency, frequency


class _Encoder:
    """low < 2^64 and 2^32 <= range < 2^64; words of 32 bits leave at the top, and a carry is added to those that left.

    Words lie by place and then lane: lanes fill up alike, so what is written at a time lies together."""

    def __init__(self, n: int, steps: int):
        self.low, self.range = np.zeros(n, np.uint64), np.full(n, (1 << 64) - 1, np.uint64)
        self.n, self.out, self.at = n, np.zeros(n * (steps + 4), np.uint32), np.arange(n)

    def narrow(self, n: int) -> None:
        self.low, self.range, self.at = self.low[:n], self.range[:n], self.at[:n]

    def put(self, cumulative: np.ndarray, frequency: np.ndarray) -> None:
        part = self.range >> _TOTAL
        gone = cumulative * part
        self.low += gone
        over = np.flatnonzero(self.low < gone)
        if len(over):
            at = self.at[over] - self.n
            while len(at):
                self.out[at] += np.uint32(1)
                at = at[self.out[at] == 0] - self.n
        np.multiply(part, frequency, out=self.range)
        need = np.flatnonzero(self.range < _U2_32)
        low = self.low.take(need)
        self.out[self.at.take(need)] = low >> _U32
        self.at[need] += self.n
        self.low[need] = low << _U32
        self.range[need] <<= _U32

    def finish(self, lane: int) -> bytes:
        n = (int(self.at[lane]) - lane) // self.n
        body = self.out[lane :: self.n][: n + 2].copy()
        body[n:] = [int(self.low[lane]) >> 32, int(self.low[lane]) & 0xFFFFFFFF]
        return body.astype("<u4").tobytes()


class _Decoder:
    def __init__(self, blocks: list[bytes]):
        n = self.n = len(blocks)
        self.range = np.full(n, (1 << 64) - 1, np.uint64)
        width = max(len(b) for b in blocks) // 4 + 4
        words = np.zeros((n, width), np.uint32)
        for i, b in enumerate(blocks):
            words[i, : len(b) // 4] = np.frombuffer(b, "<u4", len(b) // 4)
        self.code = words[:, 0].astype(np.uint64) << _U32 | words[:, 1]
        self.words, self.at, self.last = words.T.ravel(), np.arange(n) + 2 * n, (width - 1) * n

    def look(self) -> np.ndarray:
        """Where each lane's code lies in a total of 2^30."""
        self.part = self.range >> _TOTAL
        return np.minimum(self.code // self.part, _MASK)

    def take(self, cumulative: np.ndarray, frequency: np.ndarray) -> None:
        self.code -= cumulative * self.part
        np.multiply(self.part, frequency, out=self.range)
        need = np.flatnonzero(self.range < _U2_32)
        at = self.at.take(need)
        self.code[need] = self.code.take(need) << _U32 | self.words.take(np.where(at < self.last, at, need))
        self.at[need] = at + self.n
        self.range[need] <<= _U32


def encode_lanes(ids: np.ndarray, lengths: list[int]) -> list[bytes]:
    """The blocks of ids: full ones, of which only the last may be shorter."""
    n, steps = len(lengths), lengths[0]
    lanes, coder = _Lanes(n), _Encoder(n, steps)
    padded = np.zeros(n * steps, np.uint16)
    padded[: len(ids)] = ids
    rows, tail = padded.reshape(n, steps), None
    for start, end in slices(steps):
        now = rows[:, start:end].astype(np.uint32)
        flag, mixed, slot = lanes.judged(now)
        # Behind a guess there is nothing more to say.
        low = np.where(flag == 2, slot << _SPARE, np.where(flag == 3, now, np.uint32(0)))
        c, f = _span(mixed, flag)
        low, width = np.ascontiguousarray(((c << _BITS) + f * low).T), np.ascontiguousarray((f << _WIDTHS.take(flag)).T)
        for k in range(end - start):
            if start + k == lengths[-1] and tail is None:
                tail = coder.finish(n - 1)
                coder.narrow(n - 1)
            coder.put(low[k, : len(coder.low)], width[k, : len(coder.low)])
    done = [coder.finish(lane) for lane in range(len(coder.low))]
    return done if tail is None else [*done, tail]


def decode_lanes(blocks: list[bytes], lengths: list[int]) -> np.ndarray:
    n, steps = len(lengths), lengths[0]
    lanes, coder = _Lanes(n), _Decoder(blocks)
    rows = np.zeros((n, steps), np.uint16)
    # A short last block goes on beyond its end, over nothing; what it gives there is cut off.
    for start, end in slices(steps):
        columns, flags = np.zeros((end - start, n), np.uint32), np.zeros((end - start, n), np.int64)
        before, earlier, history = lanes.before, lanes.earlier, lanes.history
        for k in range(end - start):
            at_two, at_one = lanes.places(before, earlier, lanes.base)
            two, one = lanes.two.take(at_two), lanes.one.take(at_one)
            a, b = lanes.sure.take((two >> _HIGH << 2 | one >> _HIGH) + lanes.lane), lanes.past.take(history + lanes.lane)
            which, target = lanes.mixed(a, b, lanes.better), coder.look()
            ends, upper = which * _ONES, target >> _BITS
            flag = sum((upper >= (ends >> shift) & _FIELD).view(np.uint8) for shift in (_U0, _U16, _U32)).astype(np.int64)
            c, f = _span(which, flag)
            c <<= _BITS
            low = (target - c) // f
            drawn = lanes.zero.take((low >> _U_SPARE).astype(np.int64) + lanes.recent)
            now = np.where(flag < 2, np.where(flag == 0, two, one) & _NO_ID, np.where(flag == 2, drawn, low.astype(np.uint32)))
            low &= _LEFT.take(flag)
            c += f * low
            f <<= _WIDTHS.take(flag)
            coder.take(c, f)
            columns[k], flags[k] = now, flag
            history = (history << 2 | flag) & 15
            earlier, before = before, now
        rows[:, start:end] = columns.T
        lanes.judged(np.ascontiguousarray(columns.T), np.ascontiguousarray(flags.T))
    return np.concatenate([rows[i, :m] for i, m in enumerate(lengths)])


def write_file(ids: np.ndarray) -> bytes:
    """A file that holds the ids."""
    if len(ids) and (int(ids.max()) >= NO_ID or int(ids.min()) < 0):
        raise ValueError("ids must be from 0 to 65534")
    blocks, heads = [], []
    for at in range(0, len(ids), BLOCK * LANES):
        own = ids[at : at + BLOCK * LANES]
        lengths = [min(BLOCK, len(own) - b) for b in range(0, len(own), BLOCK)]
        coded = encode_lanes(own, lengths)
        heads += [struct.pack("<III", m, len(c), zlib.crc32(own[i * BLOCK : i * BLOCK + m].astype("<u4").tobytes())) for i, (m, c) in enumerate(zip(lengths, coded, strict=True))]
        blocks += coded
    return MAGIC + struct.pack("<IQII", VERSION, len(ids), len(blocks), BLOCK) + b"".join(heads) + b"".join(blocks)


def read_file(data: bytes, first_block: int = 0, end_block: int | None = None) -> np.ndarray:
    """The ids (16 bits each) of a file, or of some of its blocks; every block is held against its checksum."""
    if data[:4] != MAGIC or len(data) < 24:
        raise ValueError("not a file of ids")
    version, total, count, _ = struct.unpack_from("<IQII", data, 4)
    if version != VERSION:
        raise ValueError(f"version {version} is unknown")
    if len(data) < 24 + 12 * count:
        raise ValueError("the file is cut off")
    heads = [struct.unpack_from("<III", data, 24 + 12 * i) for i in range(count)]
    at, blocks = 24 + 12 * count, []
    for _, size, _ in heads:
        blocks.append(data[at : at + size])
        at += size
    wanted = range(count)[first_block:end_block]
    out = []
    for start in range(wanted.start, wanted.stop, LANES):
        some = range(start, min(start + LANES, wanted.stop))
        lengths = [heads[i][0] for i in some]
        if any(len(blocks[i]) != heads[i][1] or not 0 < m <= BLOCK for i, m in zip(some, lengths, strict=True)) or any(m != lengths[0] for m in lengths[:-1]) or lengths[-1] > lengths[0]:
            raise ValueError("the heads of blocks are damaged")
        ids = decode_lanes([blocks[i] for i in some], lengths)
        done = 0
        for i in some:
            own = ids[done : done + heads[i][0]]
            if zlib.crc32(own.astype("<u4").tobytes()) != heads[i][2]:
                raise ValueError(f"block {i} is damaged")
            done += len(own)
        out.append(ids)
    ids = (out[0] if len(out) == 1 else np.concatenate(out)) if out else np.empty(0, np.uint16)
    if first_block == 0 and end_block is None and len(ids) != total:
        raise ValueError("ids are missing")
    return ids


#: Chunks that are a word of ASCII and lower-case Latin-1 letters, one piece to the tokenizer, and marks behind it.
#: The apostrophe isn't among them: it starts contractions.
_PLAIN = r"^(?P<word>[A-Za-zß-öø-ÿ]+)(?P<marks>[!-&(-/:-@\[-`{-~]*)$"
#: The byte-level alphabet's letters for those bytes of such words that don't stand for themselves there.
_LETTERS = {chr(b): chr(256 + i) for i, b in enumerate(b for b in range(256) if not (33 <= b <= 126 or 161 <= b <= 172 or b >= 174)) if b > 127}


def _bytes_of(column: pa.Array) -> list[bytes]:
    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_numpy(zero_copy_only=False).tolist()


class _Store:
    """Ids of numbered pieces, one after the other; a piece's number is remembered by its bytes (bounded)."""

    def __init__(self):
        self.clear()

    def clear(self) -> None:
        self.number: dict[bytes, int] = {}
        self.parts, self.sizes = [np.empty(0, np.uint16)], [np.empty(0, np.int64)]

    def numbers(self, pieces: list[bytes], split) -> np.ndarray:
        """The pieces' numbers; ``split`` gives (ids, sizes) of those that are new."""
        known = self.number
        fresh = [*dict.fromkeys(p for p in pieces if p not in known)]
        if fresh:
            ids, sizes = split(fresh)
            self.parts.append(ids)
            self.sizes.append(sizes)
            known.update(zip(fresh, range(len(known), len(known) + len(fresh)), strict=True))
        return np.fromiter(map(known.__getitem__, pieces), np.int64, len(pieces))

    def table(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids, where each number's ids begin, how many they are)."""
        self.parts, self.sizes = [np.concatenate(self.parts)], [np.concatenate(self.sizes)]
        return self.parts[0], np.cumsum(self.sizes[0]) - self.sizes[0], self.sizes[0]


class ChunkTokenizer:
    """Encodes texts chunk by chunk (runs without ASCII white space), remembering pieces (bounded).

    The tokenizer folds white space into separators that no token crosses, so a text's ids are its chunks' ids.  A
    chunk's ASCII punctuation behind a word is a piece of its own, and a word of plain letters is one piece, which the library's
    model splits.  Every other chunk goes through the whole library call, special tokens included."""

    def __init__(self, path: str):
        env_single_thread()
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.words, self.others = _Store(), _Store()

    def encode(self, text: bytes) -> list[int]:
        return self.encode_all(pa.array([text], pa.binary()).view(pa.string()))[0].tolist()

    def encode_all(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, how many each has).  Arrow splits and numbers; only distinct pieces are looked up."""
        for store in (self.words, self.others):
            if len(store.number) > _CACHE_LIMIT:
                store.clear()
        cut = pc.ascii_split_whitespace(texts)
        coded = pc.list_flatten(cut).dictionary_encode()
        chunks = coded.dictionary
        cuts = pc.extract_regex(chunks, _PLAIN)
        plain = np.asarray(pc.is_valid(cuts))
        word = pc.struct_field(cuts, "word").filter(pa.array(plain))
        stems = pc.ascii_lower(word).dictionary_encode()
        marks = pc.struct_field(cuts, "marks").filter(pa.array(plain)).dictionary_encode()
        # Of each distinct chunk its word and marks, or the whole of it and nothing.
        first, second = np.zeros(len(chunks), np.int64), np.zeros(len(chunks), np.int64)
        at = self.words.numbers(_bytes_of(stems.dictionary), self._split)
        other = self.others.numbers([b"", *_bytes_of(marks.dictionary), *_bytes_of(chunks.filter(pa.array(~plain)))], self._whole)
        ids, starts, sizes = self.words.table()
        more, more_starts, more_sizes = self.others.table()
        n, m = len(sizes), len(marks.dictionary)
        first[plain], second[plain] = at[np.asarray(stems.indices)], n + other[1 + np.asarray(marks.indices)]
        first[~plain], second[~plain] = n + other[1 + m :], n + other[0]
        ids, starts, sizes = np.concatenate([ids, more]), np.concatenate([starts, len(ids) + more_starts]), np.concatenate([sizes, more_sizes])
        return _gathered(ids, starts, sizes, np.stack([first, second], 1)[np.asarray(coded.indices)].ravel(), 2 * (np.asarray(cut.offsets) - cut.offsets[0].as_py()))

    def _split(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Words of plain letters by the library's model, in its byte-level alphabet."""
        split, ids, sizes = self.tokenizer.model.tokenize, [], []
        for at in range(0, len(words), 20_000):
            text = b" ".join(words[at : at + 20_000]).decode("latin-1")
            for byte, letter in _LETTERS.items():
                text = text.replace(byte, letter)
            for word in text.split(" "):
                found = split(word)
                sizes.append(len(found))
                ids += [t.id for t in found]
        return np.array(ids, np.uint16), np.array(sizes, np.int64)

    def _whole(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        out = [np.empty(0, np.uint16)]
        for at in range(0, len(texts), 50_000):
            out += [np.array(e.ids, np.uint16) for e in self.tokenizer.encode_batch_fast([t.decode("utf-8", "replace") for t in texts[at : at + 50_000]], add_special_tokens=False)]
        return np.concatenate(out), np.array([len(x) for x in out[1:]], np.int64)


def _gathered(ids: np.ndarray, starts: np.ndarray, sizes: np.ndarray, pieces: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(the ids of numbered pieces in order, how many of them lie between the bounds)."""
    each = sizes[pieces]
    ends = np.append(0, np.cumsum(each))
    return ids[np.repeat(starts[pieces] - ends[:-1], each) + np.arange(ends[-1])], np.diff(ends[bounds])


@functools.lru_cache(maxsize=2)
def tokenizer(path: str) -> ChunkTokenizer:
    return ChunkTokenizer(path)


def _groups(sizes: list[int]) -> Iterator[tuple[int, int]]:
    """Spans of texts that are encoded together: of _GROUP_BYTES, or one text."""
    start, size = 0, 0
    for at, more in enumerate(sizes):
        if size and size + more > _GROUP_BYTES:
            yield start, at
            start, size = at, 0
        size += more
    if sizes:
        yield start, len(sizes)


FILE_SCHEMA = "part int, shard int, n_tokens long, file binary, doc_ids binary, lengths binary"


def _written(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, shard, coder = TaskContext.get().partitionId(), 0, tokenizer(path)
        ids: list[np.ndarray] = []
        lengths: list[np.ndarray] = []
        owners: list[pa.Array] = []
        size = 0

        def flush():
            names, body = pa.concat_arrays(owners), np.concatenate(ids)
            marks = np.stack([names.is_valid().to_numpy(zero_copy_only=False).astype("<i8"), names.fill_null(0).to_numpy(zero_copy_only=False)], 1)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([shard], pa.int32()), pa.array([len(body)], pa.int64()), pa.array([write_file(body)], pa.binary()), pa.array([marks.tobytes()], pa.binary()), pa.array([np.concatenate(lengths).astype("<i8").tobytes()], pa.binary())], [f.split()[0] for f in FILE_SCHEMA.split(", ")])

        for batch in batches:
            docs, texts = batch.column(0).cast(pa.int64()), batch.column(1).cast(pa.large_string()).fill_null("")
            for a, b in _groups(pc.binary_length(texts).to_pylist()):
                own, each = coder.encode_all(texts[a:b])
                ids.append(np.insert(own, np.cumsum(each), end_id))
                lengths.append(each + 1)
                owners.append(docs[a:b])
                size += len(ids[-1])
                if size >= BLOCK * LANES:
                    yield flush()
                    ids, lengths, owners, size, shard = [], [], [], 0, shard + 1
        if ids:
            yield flush()

    return run


def write_ids(docs: DataFrame, path: str | None = None, end_id: int = END_ID) -> DataFrame:
    """Tokenize every whole text and write the ids' files, in ascending order of doc_id, as a table in the shared folder."""
    spark = docs.sparkSession
    ship(spark)
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    rows = drop_suffix(docs, ["doc_id", "text"]).withColumn("doc_id", F.col("doc_id").cast("long"))
    parts = buckets_for(text_bytes(docs), _PARTITION_BYTES)
    dealt = rows.repartitionByRange(parts, "doc_id").sortWithinPartitions("doc_id", "text")
    return scratch(spark, dealt.mapInArrow(_written(path, end_id), FILE_SCHEMA), "ids")


def _read_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for row in batch.to_pylist():
            ids = read_file(row["file"])
            raw = ids.astype("<u4")
            lengths = np.frombuffer(row["lengths"], "<i8")
            marks = np.frombuffer(row["doc_ids"], "<i8").reshape(-1, 2)
            ends = np.cumsum(lengths)
            starts = ends - lengths
            sums = [zlib.crc32(raw[a:b]) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
            n = len(lengths)
            yield pa.RecordBatch.from_arrays([pa.array([row["part"]] * n, pa.int32()), pa.array([row["shard"]] * n, pa.int32()), pa.array(marks[:, 1], mask=marks[:, 0] == 0), pa.array(starts), pa.array(lengths.astype(np.int64)), pa.array(sums, pa.int64())], ["part", "shard", "doc_id", "inside", "n_tokens", "ids_crc32"])


def read_ids(files: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files."""
    order = Window.orderBy("part", "shard").rowsBetween(Window.unboundedPreceding, -1)
    # One row of three numbers for each file of some four million ids.
    before = files.select("part", "shard", "n_tokens").select("part", "shard", F.coalesce(F.sum("n_tokens").over(order), F.lit(0)).alias("before"))
    rows = files.mapInArrow(_read_rows, "part int, shard int, doc_id long, inside long, n_tokens long, ids_crc32 long")
    return rows.join(before, ["part", "shard"]).select("doc_id", (F.col("before") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32")


def op1_id_coder(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_ids(write_ids(read_documents(spark, sf_dir)))
