"""N-gram language model in a sharded trie of Elias-Fano levels, memory-mapped by the scoring tasks.

Level 1 holds every word of the training texts (64-bit hash, count), ordered by hash, and cut into
shards by the hash's leading bits. Level 2 holds, under each first word, its successors; level 3
holds, under each word pair, the *positions of the third word among the successors of the second*,
a far smaller range than word numbers. Each level is one monotone Elias-Fano sequence (every range
is shifted by the end of the range before it) with Elias-Fano pointers to the ranges, and one byte
per entry for its quantised discounted probability and for the mass left to shorter contexts. A
lookup goes to the high-bit bucket of the value sought and halves it.

Probability of a word after two words: discounted share of the triple, plus the mass left of the
pair times the same for the second word alone, plus the mass left of that word times the smoothed
word frequency. All pairs and triples of all training texts enter, or those from ``least`` occurrences on.

Tasks count keys of their own texts by sorting and hand on one block of bytes per shard, not rows. A
shard of levels 2 and 3 is a range of keys that about ``shard_tokens`` counted tokens fall into: the
level above knows how often each of its entries is a context. The range of a context that occurs
more often than that is cut by the following word. So no task's share grows with the corpus; the
number of shards does.
"""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .runtime import get_arrays, new_path, put_arrays, settle, ship

_U = np.uint64
#: Hashes of the end token (counted) and of the start of a text (context only).
END, START = (K.mix(np.array([11, 23], _U)) | _U(1)).tolist()
#: Words that a shard of the first level holds, about; tokens that the entries of a shard of the others count, about.
SHARD_WORDS, SHARD_TOKENS = 1 << 20, 3 << 20
#: Keys that a task sorts at a time; text bytes that are looked up at a time; bytes of shards that a task keeps open.
HELD, SLICE, OPEN_BYTES = 1 << 22, 6 << 20, 256 << 20
#: The smallest log10 that a byte can stand for; codes lie on a square scale, finest near probability 1.
FLOOR = -9.0

_NTH = np.full((256, 8), 8, np.int64)
for _b in range(256):
    for _k, _p in enumerate(p for p in range(8) if _b >> p & 1):
        _NTH[_b, _k] = _p
_NTH = _NTH.ravel()
_ONES, _TOPS = _U(0x0101010101010101), _U(0x8080808080808080)


def _byte_sums(x: np.ndarray) -> np.ndarray:
    """In byte i, the number of set bits of bytes 0 to i."""
    x = x - ((x >> _U(1)) & _U(0x5555555555555555))
    x = (x & _U(0x3333333333333333)) + ((x >> _U(2)) & _U(0x3333333333333333))
    x = (x + (x >> _U(4))) & _U(0x0F0F0F0F0F0F0F0F)
    x *= _ONES
    return x


def _pack_bits(values: np.ndarray, bits: int) -> np.ndarray:
    """The low bits of all values, one after the other."""
    out = np.zeros(len(values) * bits // 64 + 2, _U)
    if not bits or not len(values):
        return out
    low = values & _U((1 << bits) - 1)
    at = np.arange(len(values), dtype=np.int64) * bits
    word, shift = at >> 6, (at & 63).astype(_U)
    starts = np.flatnonzero(np.diff(word, prepend=-1))
    out[word[starts]] = np.bitwise_or.reduceat(low << shift, starts)
    over = np.flatnonzero((at & 63) + bits > 64)
    out[word[over] + 1] |= low[over] >> (_U(64) - shift[over])
    return out


class EliasFano:
    """A non-decreasing sequence of non-negative integers: low bits packed, high bits in unary."""

    def __init__(self, n: int, low_bits: int, low: np.ndarray, high: np.ndarray, ones: np.ndarray):
        self.n, self.low_bits, self.low, self.high = n, low_bits, low, high
        self.ones = ones.astype(np.int64)  # set bits before each word of high
        self.zeros = 64 * np.arange(len(self.ones), dtype=np.int64) - self.ones

    @staticmethod
    def pack(values: np.ndarray) -> dict[str, np.ndarray]:
        values = np.asarray(values, _U)
        n = len(values)
        top = int(values[-1]) + 1 if n else 1
        bits = max(0, (top // max(n, 1)).bit_length() - 1)
        high_len = (n + (top >> bits) + 1) // 64 + 2
        flags = np.zeros(high_len * 64, np.uint8)
        flags[(values >> _U(bits)).astype(np.int64) + np.arange(n)] = 1
        high = np.packbits(flags, bitorder="little").view(_U)
        ones = np.concatenate([[0], np.cumsum(np.bitwise_count(high), dtype=np.int64)])[:-1]
        return {"shape": np.array([n, bits], np.int64), "low": _pack_bits(values, bits), "high": high, "ones": ones.astype(np.uint32)}

    @classmethod
    def of(cls, parts: dict[str, np.ndarray]) -> EliasFano:
        n, bits = parts["shape"].tolist()
        return cls(n, bits, parts["low"], parts["high"], parts["ones"])

    def _select(self, k: np.ndarray, before: np.ndarray, flip: bool) -> np.ndarray:
        """Bit position of the k-th (from 0) set bit, or clear bit with flip."""
        word = np.searchsorted(before, k, "right") - 1
        inside = self.high[word]
        if flip:
            inside = ~inside
        upto = _byte_sums(inside)
        left = (k - before[word]).astype(_U)
        byte = np.bitwise_count((left * _ONES | _TOPS) - upto & _TOPS).astype(_U)  # bytes that end before it
        skip = byte << _U(3)
        left -= (upto << _U(8)) >> skip & _U(255)
        return (word << 6) + skip.astype(np.int64) + _NTH[((inside >> skip & _U(255)) << _U(3) | left).astype(np.int64)]

    def low_at(self, i: np.ndarray) -> np.ndarray:
        if not self.low_bits:
            return np.zeros(len(i), _U)
        bit = i * self.low_bits
        word, shift = bit >> 6, (bit & 63).astype(_U)
        wide = self.low[word] >> shift
        more = np.where(shift > 0, self.low[word + 1] << ((_U(64) - shift) & _U(63)), _U(0))
        return (wide | more) & _U((1 << self.low_bits) - 1)

    def get(self, i: np.ndarray) -> np.ndarray:
        if not len(i):
            return np.zeros(0, np.int64)
        high = self._select(i, self.ones, False) - i
        return (high << self.low_bits) | self.low_at(i).astype(np.int64)

    def find(self, value: np.ndarray, first: np.ndarray, stop: np.ndarray) -> np.ndarray:
        """Index in [first, stop) of each value, -1 where it is not there."""
        out = np.full(len(value), -1, np.int64)
        if not len(value) or not self.n:
            return out
        high, low = value >> self.low_bits, (value & ((1 << self.low_bits) - 1)).astype(_U)
        inside = (stop > first) & (high < self.zeros[-1])
        live = np.flatnonzero(inside)
        h, low = high[live], low[live]
        lo = np.where(h > 0, self._select(np.maximum(h - 1, 0), self.zeros, True) + 1 - h, 0)
        hi = self._select(h, self.zeros, True) - h
        lo, hi = np.maximum(lo, first[live]), np.minimum(hi, stop[live])
        on = lo < hi
        live, lo, hi, low = live[on], lo[on], hi[on], low[on]
        end = hi.copy()
        while True:  # most buckets hold an entry or two; those of dense ranges are halved
            wide = np.flatnonzero(hi - lo > 1)
            if not len(wide):
                break
            middle = (lo[wide] + hi[wide]) >> 1
            right = self.low_at(middle) <= low[wide]
            lo[wide[right]] = middle[right]
            hi[wide[~right]] = middle[~right]
        hit = (lo < end) & (self.low_at(np.minimum(lo, self.n - 1)) == low)
        out[live[hit]] = lo[hit]
        return out


def quantise(p: np.ndarray) -> np.ndarray:
    """One byte per probability: steps of 0.0001 in log10 near 1, of 0.05 near 10^-4."""
    depth = np.log10(np.maximum(p, 1e-12)) / FLOOR
    return np.clip(np.rint(255 * np.sqrt(np.maximum(depth, 0))), 0, 255).astype(np.uint8)


CODE = 10.0 ** (FLOOR * (np.arange(256) / 255) ** 2)


def _nest(arrays: dict[str, np.ndarray], prefix: str) -> EliasFano:
    return EliasFano.of({k[len(prefix) :]: v for k, v in arrays.items() if k.startswith(prefix)})


def _ranges(owner: np.ndarray, value: np.ndarray, owners: int) -> tuple[dict, dict]:
    """Pointers and shifted values of entries sorted by (owner, value)."""
    pointer = np.searchsorted(owner, np.arange(owners + 1))
    filled = np.flatnonzero(np.diff(pointer))
    last = value[pointer[filled + 1] - 1] + 1
    base = np.zeros(owners + 1, np.int64)
    base[filled + 1] = last
    base = np.cumsum(base)[:-1]
    return EliasFano.pack(pointer), EliasFano.pack(value + 1 + base[owner])


@dataclass
class Level:
    """Where the shards of successors start: as keys (owner and value) and in the common numbering of entries.

    Owners that are cut into several shards have these for themselves; where their entries start and the
    mass that they leave stand here."""

    value_bits: int = 1
    bounds: np.ndarray = field(default_factory=lambda: np.zeros(0, _U))
    owners: int = 0
    at: np.ndarray = field(default_factory=lambda: np.zeros(1, np.int64))
    cut_owner: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    cut_first: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    cut_left: np.ndarray = field(default_factory=lambda: np.zeros(0))

    def owners_of(self, shard: int) -> tuple[int, int]:
        """First owner of a shard, and the one behind its last."""
        first = int(self.bounds[shard]) >> self.value_bits
        return first, (int(self.bounds[shard + 1]) - 1 >> self.value_bits) + 1 if shard + 1 < len(self.bounds) else self.owners


@dataclass
class Layout:
    """Where the shards are, and what all tasks know of them."""

    folder: str
    bits: int
    words_at: np.ndarray
    total: int = 0
    distinct: int = 0
    discount: float = 0.6
    least: int = 1
    shard_tokens: int = SHARD_TOKENS
    pairs: Level = field(default_factory=Level)
    triples: Level = field(default_factory=Level)


class Trie:
    """The levels as a task sees them; shards are opened when needed, those used last stay open."""

    def __init__(self, layout: Layout):
        self.at = layout
        self.open: OrderedDict[tuple[str, int], dict] = OrderedDict()
        self.size = 0

    def level(self, kind: str, shard: int) -> dict:
        if (got := self.open.get((kind, shard))) is None:
            got = get_arrays(f"{self.at.folder}/{kind}-{shard}.bin")
            self.size += sum(x.nbytes for x in got.values())
            for name in {k.split(".")[0] for k in got if "." in k}:
                got[name] = _nest(got, f"{name}.")
            self.open[kind, shard] = got
            while self.size > OPEN_BYTES and len(self.open) > 1:
                self.size -= sum(x.nbytes for x in self.open.popitem(last=False)[1].values() if isinstance(x, np.ndarray))
        else:
            self.open.move_to_end((kind, shard))
        return got

    def words(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(number, count) of hashes; the number of words and 0 for unknown ones."""
        number, count = np.full(len(hashes), self.at.words_at[-1], np.int64), np.zeros(len(hashes), np.int64)
        bits = self.at.bits
        shard = (hashes >> _U(64 - bits)).astype(np.int64) if bits else np.zeros(len(hashes), np.int64)
        order = np.argsort(shard.astype(np.uint16) if bits <= 16 else shard, kind="stable")
        for s, a, b in _groups(shard[order]):
            if self.at.words_at[s + 1] == self.at.words_at[s]:
                continue
            one, rows = self.level("words", s), order[a:b]
            sought, table = hashes[rows], one["hash"]
            bucket = (sought << _U(bits)) >> _U(65 - (len(one["bucket"]) - 1).bit_length())
            i, stop = one["bucket"][bucket].astype(np.int64), one["bucket"][bucket + _U(1)].astype(np.int64)
            on = np.flatnonzero(i < stop)
            while len(on):  # about one entry a bucket
                on = on[table[i[on]] < sought[on]]
                i[on] += 1
                on = on[i[on] < stop[on]]
            hit = np.flatnonzero(i < stop)
            hit = hit[table[i[hit]] == sought[hit]]
            number[rows[hit]] = i[hit] + self.at.words_at[s]
            count[rows[hit]] = one["count"][i[hit]]
        return number, count

    def entries(self, kind: str, owner: np.ndarray, value: np.ndarray):
        """Entries (owner, value), sorted by owner: (number or -1, place in the owner's range, share, mass the owner leaves)."""
        at: Level = getattr(self.at, kind)
        number, place, share, left = np.full(len(owner), -1, np.int64), np.zeros(len(owner), np.int64), np.zeros(len(owner)), np.ones(len(owner))
        if not len(owner) or not len(at.bounds):
            return number, place, share, left
        shard = np.searchsorted(at.bounds, (owner.astype(_U) << _U(at.value_bits)) | value.astype(_U), "right") - 1
        if (shard[1:] < shard[:-1]).any():  # an owner's range that is cut, its values in no order
            order = np.argsort(shard, kind="stable")
            found = self.entries(kind, owner[order], value[order])
            for out, x in zip((number, place, share, left), found):
                out[order] = x
            return number, place, share, left
        for s, a, b in _groups(shard):
            if at.at[s + 1] == at.at[s]:
                continue
            one = self.level(kind, s)
            own = owner[a:b] - at.owners_of(s)[0]
            heads = np.flatnonzero(np.diff(own, prepend=-1))
            times, own = np.diff(heads, append=b - a), own[heads]
            first, stop = one["range"].get(own), one["range"].get(own + 1)
            base = np.where(first > 0, one["next"].get(np.maximum(first - 1, 0)), 0)
            start = np.repeat(first, times)
            i = one["next"].find(value[a:b] + 1 + np.repeat(base, times), start, np.repeat(stop, times))
            hit = np.flatnonzero(i >= 0)
            number[a + hit], place[a + hit], share[a + hit] = i[hit] + at.at[s], (i - start)[hit], CODE[one["share"][i[hit]]]
            left[a:b] = np.repeat(CODE[one["left"][own]], times)
        if len(at.cut_owner):
            j = np.minimum(np.searchsorted(at.cut_owner, owner), len(at.cut_owner) - 1)
            here = at.cut_owner[j] == owner
            left = np.where(here, at.cut_left[j], left)
            place = np.where(here & (number >= 0), number - at.cut_first[j], place)
        return number, place, share, left


def _groups(shards: np.ndarray):
    """(value, begin, end) of each run of a sorted array."""
    if len(shards):
        cut = np.flatnonzero(np.diff(shards)) + 1
        for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(shards)]):
            yield int(shards[a]), a, b


def _tokens(body, offsets):
    """Hashes of each row's tokens with START before and END behind them; tokens per row with both."""
    hashes, counts, _, _ = K.words(body, offsets)
    full = counts + 2
    out = np.full(int(full.sum()), END, _U)
    begin = np.cumsum(full) - full
    out[begin] = START
    out[K.spread(begin + 1, counts)] = hashes
    return out, full


# -- counts on their way to the shards ------------------------------------------------------------------


def _runs(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct sorted keys and how often each comes."""
    keys = np.sort(keys)
    at = np.flatnonzero(np.concatenate([np.ones(min(1, len(keys)), bool), keys[1:] != keys[:-1]]))
    return keys[at], np.diff(at, append=len(keys))


def _held(stream: Iterator[np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Keys of a task and their counts, by ``HELD`` tokens at a time."""
    held, size = [], 0
    for keys in stream:
        held.append(keys)
        size += len(keys)
        if size >= HELD:
            yield _runs(np.concatenate(held))
            held, size = [], 0
            K.give_back()
    if size:
        yield _runs(np.concatenate(held))


def encode_counts(keys: np.ndarray, counts: np.ndarray, low: int) -> bytes:
    """Sorted distinct keys from ``low`` on and their counts: steps by planes of bytes, counts in a byte, large ones apart."""
    steps = np.diff(keys, prepend=_U(low))
    width = max(1, -(-int(steps.max()).bit_length() // 8))
    planes = np.ascontiguousarray(steps.view(np.uint8).reshape(-1, 8)[:, :width].T)
    large = counts[counts >= 255]
    head = np.array([len(keys), width, len(large)], np.int64)
    return b"".join((head.tobytes(), large.astype(np.int64).tobytes(), planes.tobytes(), np.minimum(counts, 255).astype(np.uint8).tobytes()))


def decode_counts(body: bytes, low: int) -> tuple[np.ndarray, np.ndarray]:
    n, width, large = np.frombuffer(body, np.int64, 3).tolist()
    at = 24 + 8 * large
    steps = np.zeros((n, 8), np.uint8)
    steps[:, :width] = np.frombuffer(body, np.uint8, n * width, at).reshape(width, n).T
    counts = np.frombuffer(body, np.uint8, n, at + n * width).astype(np.int64)
    counts[counts == 255] = np.frombuffer(body, np.int64, large, 24)
    keys = steps.view(_U).ravel()
    keys[0] += _U(low)
    return np.cumsum(keys, dtype=_U), counts


def merge_counts(bodies, low: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys and summed counts of a shard's blocks. Counts below 16 are sorted as repeated keys, which is
    faster than sorting keys with their counts, and as many as the shard was made for; others are added."""
    if not len(bodies):
        return np.zeros(0, _U), np.zeros(0, np.int64)
    keys, counts = (np.concatenate(x) for x in zip(*(decode_counts(b, low) for b in bodies)))
    large = np.flatnonzero(counts >= 16)
    more, where = counts[large] - 1, keys[large]
    counts[large] = 1
    keys, counts = _runs(np.repeat(keys, counts))
    np.add.at(counts, np.searchsorted(keys, where), more)
    return keys, counts


def _word_tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for words, counts in _held(_tokens(body, offsets)[0] for batch in batches for _, _, body, offsets in K.slices(batch, "text", SLICE)):
        for i in range(0, len(words), 1 << 17):
            yield pa.RecordBatch.from_arrays([pa.array(words[i : i + (1 << 17)].view(np.int64)), pa.array(counts[i : i + (1 << 17)])], names=["word", "n"])


def _dealt(stream: Iterator[np.ndarray], bounds: np.ndarray) -> Iterator[pa.RecordBatch]:
    """(shard, block of counts)."""
    for keys, counts in _held(stream):
        cut = [0, *np.searchsorted(keys, bounds[1:]).tolist(), len(keys)]
        full = [s for s in range(len(bounds)) if cut[s] < cut[s + 1]]
        blocks = [encode_counts(keys[cut[s] : cut[s + 1]], counts[cut[s] : cut[s + 1]], int(bounds[s])) for s in full]
        yield pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array(blocks, pa.binary())], names=["shard", "body"])


def _order(key: np.ndarray) -> np.ndarray:
    """Places of the keys in ascending order, but for low bits that find no room beside a place."""
    bits = max(1, (len(key) - 1).bit_length())
    cut = max(0, int(key.max()).bit_length() + bits - 64) if len(key) else 0
    return (np.sort(((key >> _U(cut)) << _U(bits)) | np.arange(len(key), dtype=_U)) & _U((1 << bits) - 1)).astype(np.int64)


class _Lookup:
    """Numbers of a slice's tokens, pairs and triples."""

    def __init__(self, trie: Trie, body: np.ndarray, offsets: np.ndarray):
        self.trie = trie
        hashes, self.full = _tokens(body, offsets)
        coded = pa.array(hashes).dictionary_encode()
        number, count = trie.words(coded.dictionary.to_numpy())
        back = coded.indices.to_numpy()
        none = trie.at.words_at[-1]
        self.number, self.count = np.where(count >= trie.at.least, number, none)[back], count[back]
        inner = np.ones(len(hashes), bool)
        begin = np.cumsum(self.full) - self.full
        inner[begin] = False
        self.at = np.flatnonzero(inner)  # every token but START
        self.second = inner.copy()
        self.second[begin + 1] = False  # tokens with two tokens before them

    def _found(self, kind: str, j: np.ndarray, owner: np.ndarray, value: np.ndarray):
        """Tokens j in the order of their keys, with what the trie has."""
        order = _order((owner.astype(_U) << _U(getattr(self.trie.at, kind).value_bits)) | value.astype(_U))
        return j[order], *self.trie.entries(kind, owner[order], value[order])

    def pair_keys(self) -> np.ndarray:
        none, j = self.trie.at.words_at[-1], self.at
        j = j[(self.number[j] < none) & (self.number[j - 1] < none)]
        return (self.number[j - 1].astype(_U) << _U(self.trie.at.pairs.value_bits)) | self.number[j].astype(_U)

    def find_pairs(self):
        """Per token: number of the pair that ends in it (-1) and its place; (tokens, share, mass left) of those with a known word before."""
        self.pair, self.place = np.full(len(self.number), -1, np.int64), np.zeros(len(self.number), np.int64)
        j = self.at[self.number[self.at - 1] < self.trie.at.words_at[-1]]
        j, number, place, share, left = self._found("pairs", j, self.number[j - 1], self.number[j])
        self.pair[j], self.place[j] = number, place
        return j, share, left

    def triple_keys(self) -> np.ndarray:
        j = np.flatnonzero(self.second)
        j = j[(self.pair[j] >= 0) & (self.pair[j - 1] >= 0)]
        return (self.pair[j - 1].astype(_U) << _U(self.trie.at.triples.value_bits)) | self.place[j].astype(_U)

    def find_triples(self):
        """(tokens, share, mass left) of those with a known pair before."""
        j = np.flatnonzero(self.second)
        j = j[self.pair[j - 1] >= 0]
        none = (1 << self.trie.at.triples.value_bits) - 1  # no place: such triples are not there
        j, _, _, share, left = self._found("triples", j, self.pair[j - 1], np.where(self.pair[j] >= 0, self.place[j], none))
        return j, share, left


def _slices(batches: Iterator[pa.RecordBatch], layout: Layout) -> Iterator[_Lookup]:
    trie = Trie(layout)
    for batch in batches:
        for _, _, body, offsets in K.slices(batch, "text", SLICE):
            yield _Lookup(trie, body, offsets)


def _pair_tally(batches, layout):
    return _dealt((one.pair_keys() for one in _slices(batches, layout)), layout.pairs.bounds)


def _triple_tally(batches, layout):
    return _dealt((one.find_pairs() and one.triple_keys() for one in _slices(batches, layout)), layout.triples.bounds)


# -- shards -------------------------------------------------------------------------------------------------

_BUILT = "shard int, n long, mass double, most long, cuts array<long>, parts array<long>"


def _built(shard: int, counts: np.ndarray, tokens: int, mass: float = 0.0, most: int = 0) -> pd.DataFrame:
    """A row on a built shard. cuts: entries that shards of the next level start at; parts: into how many each is cut."""
    before = (np.cumsum(counts) - counts) // tokens
    heavy = np.flatnonzero(counts > tokens)
    starts = np.unique(np.concatenate([np.flatnonzero(np.diff(before, prepend=-1)), heavy, heavy + 1]))
    starts = starts[starts < len(counts)].astype(np.int64)
    parts = np.where(counts[starts] > tokens, -(-counts[starts] // tokens), 1)
    return pd.DataFrame({"shard": [shard], "n": [len(counts)], "mass": [mass], "most": [most], "cuts": [starts], "parts": [parts]})


def _build_words(part: pd.DataFrame, folder: str, bits: int, tokens: int) -> pd.DataFrame:
    shard = int(part["shard"].iloc[0])
    hashes = part["word"].to_numpy(np.int64).view(_U)
    order = np.argsort(hashes)
    hashes, counts = hashes[order], part["n"].to_numpy(np.int64)[order]
    wide = max(1, len(hashes).bit_length())
    bucket = np.searchsorted((hashes << _U(bits)) >> _U(64 - wide), np.arange((1 << wide) + 1, dtype=_U)).astype(np.uint32)
    put_arrays(f"{folder}/words-{shard}.bin", {"hash": hashes, "count": counts, "bucket": bucket})
    return _built(shard, counts, tokens)


def _build(part: pd.DataFrame, layout: Layout, kind: str) -> pd.DataFrame:
    """Entries of a shard, and, of pairs, their counts for the level below."""
    level: Level = getattr(layout, kind)
    shard = int(part["shard"].iloc[0])
    keys, counts = merge_counts(part["body"].tolist(), int(level.bounds[shard]))
    if layout.least > 1:
        keys, counts = keys[counts >= layout.least], counts[counts >= layout.least]
    first, stop = level.owners_of(shard)
    owner = (keys >> _U(level.value_bits)).astype(np.int64) - first
    value = (keys & _U((1 << level.value_bits) - 1)).astype(np.int64)
    above = layout.words_at if kind == "pairs" else layout.pairs.at
    up = int(np.searchsorted(above, first, "right")) - 1
    context = get_arrays(f"{layout.folder}/{'words' if kind == 'pairs' else 'paircounts'}-{up}.bin")
    context = _small_counts(context)[first - above[up] : stop - above[up]] if kind == "triples" else context["count"][first - above[up] : stop - above[up]]
    share = (counts - layout.discount) / context[owner]
    given = np.bincount(owner, weights=share, minlength=len(context))
    left = np.where(np.bincount(owner, minlength=len(context)) > 0, np.maximum(1 - given, 1e-9), 1.0)
    pointers, following = _ranges(owner, value, len(context))
    if len(keys):
        arrays = {f"range.{k}": v for k, v in pointers.items()} | {f"next.{k}": v for k, v in following.items()}
        put_arrays(f"{layout.folder}/{kind}-{shard}.bin", arrays | {"share": quantise(share), "left": quantise(left)})
    if kind == "pairs" and len(keys):
        large = np.flatnonzero(counts >= 255)
        put_arrays(f"{layout.folder}/paircounts-{shard}.bin", {"small": np.minimum(counts, 255).astype(np.uint8), "where": large, "large": counts[large]})
    return _built(shard, counts, layout.shard_tokens, float(share.sum()), int(np.bincount(owner).max(initial=0)))


def _builder(layout: Layout, kind: str):
    return lambda part: _build(part, layout, kind)


def _small_counts(arrays: dict[str, np.ndarray]) -> np.ndarray:
    counts = arrays["small"].astype(np.int64)
    counts[arrays["where"]] = arrays["large"]
    return counts


class _Sizes:
    """What the built shards of a level say, in order: one row of a few numbers per shard."""

    def __init__(self, built: DataFrame, shards: int):
        self.n, self.mass, self.most = np.zeros(shards, np.int64), np.zeros(shards), np.zeros(shards, np.int64)
        self.cuts: list[tuple[int, int, int]] = []
        for row in built.collect():
            s = row["shard"]
            self.n[s], self.mass[s], self.most[s] = row["n"], row["mass"], row["most"]
            self.cuts += [(s, c, k) for c, k in zip(row["cuts"], row["parts"])]
        self.at = np.concatenate([[0], np.cumsum(self.n)])
        self.cuts.sort()

    def level_below(self, most_values: int) -> Level:
        """Bounds of the next level, whose values are below ``most_values``; that number itself stands for no value."""
        bits = max(1, int(most_values).bit_length())
        if int(self.at[-1]).bit_length() + bits > 64:
            raise OverflowError(f"{self.at[-1]} entries, each followed by up to {most_values}: keys need more than 64 bits")
        keys = [(int(self.at[s]) + c << bits) + j * int(most_values) // k for s, c, k in self.cuts for j in range(k)]
        return Level(bits, np.array(keys, _U), int(self.at[-1]))


def _close(level: Level, sizes: _Sizes) -> int:
    """Enter the numbers of entries and what is known of owners that are cut; the most entries of an owner."""
    level.at = sizes.at
    owner = (level.bounds >> _U(level.value_bits)).astype(np.int64)
    runs = [(a, b) for _, a, b in _groups(owner) if b - a > 1]
    level.cut_owner = np.array([owner[a] for a, _ in runs], np.int64)
    level.cut_first = np.array([sizes.at[a] for a, _ in runs], np.int64)
    level.cut_left = np.array([max(1 - sizes.mass[a:b].sum(), 1e-9) if sizes.n[a:b].any() else 1.0 for a, b in runs])
    return max([int(sizes.most.max(initial=0)), *(int(sizes.n[a:b].sum()) for a, b in runs)])


def train(texts: DataFrame, least: int = 1, discount: float = 0.6, shard_words: int = SHARD_WORDS, shard_tokens: int = SHARD_TOKENS) -> Layout:
    """Build the trie of all rows of ``texts`` (text; null is empty) in the shared folder.

    The driver holds a few numbers per shard. Raises OverflowError where keys would need more than 64 bits
    (word numbers twice, or pair numbers and the successors of a word)."""
    spark = texts.sparkSession
    ship(spark)
    texts = texts.select(F.col("text").cast("string").alias("text"))
    folder = new_path(spark, "trie")
    words = settle(texts.mapInArrow(_word_tally, "word long, n long").groupBy("word").agg(F.sum("n").alias("n")), "words")
    start = START - (1 << 64) if START >= 1 << 63 else START
    sums = words.where(F.col("word") != start).agg(F.count("*").alias("v"), F.sum("n").alias("n")).first()
    bits = (int(sums["v"]) // shard_words).bit_length()
    of_word = F.shiftrightunsigned("word", 64 - bits).cast("int") if bits else F.lit(0)
    built = words.select(of_word.alias("shard"), "word", "n").groupBy("shard").applyInPandas(lambda p: _build_words(p, folder, bits, shard_tokens), _BUILT)
    sizes = _Sizes(settle(built, "sizes"), 1 << bits)
    layout = Layout(folder, bits, sizes.at, int(sums["n"] or 0), int(sums["v"]), discount, least, shard_tokens, pairs=sizes.level_below(int(sizes.at[-1])))
    for kind, tally in (("pairs", _pair_tally), ("triples", _triple_tally)):
        level = getattr(layout, kind)
        dealt = texts.mapInArrow(lambda it, f=tally: f(it, layout), "shard int, body binary")
        built = dealt.groupBy("shard").applyInPandas(_builder(layout, kind), _BUILT)
        sizes = _Sizes(settle(built, "sizes"), len(level.bounds))
        most = _close(level, sizes)
        if kind == "pairs":
            layout.triples = sizes.level_below(most)
    return layout


def _score(batches: Iterator[pa.RecordBatch], layout: Layout) -> Iterator[pa.RecordBatch]:
    trie = Trie(layout)
    floor = layout.total + 0.1 * (layout.distinct + 1)
    for batch in batches:
        for i, j, body, offsets in K.slices(batch, "text", SLICE):
            one = _Lookup(trie, body, offsets)
            plain = (one.count + 0.1) / floor
            p = plain.copy()
            rows, share, left = one.find_pairs()
            p[rows] = share + left * p[rows]
            rows, share, left = one.find_triples()
            p[rows] = share + left * p[rows]
            at, counts = one.at, one.full - 1
            columns = [
                batch.column(0).slice(i, j - i),
                pa.array(counts),
                pa.array(K.segment_sums((one.count[at] > 0).astype(np.int64), counts).astype(np.int64)),
                pa.array(K.segment_sums(np.log10(plain[at]), counts)),
                pa.array(K.segment_sums(np.log10(np.minimum(p[at], 1.0)), counts)),
            ]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_tokens", "n_known", "base_score", "score"])


def score(docs: DataFrame, layout: Layout) -> DataFrame:
    """(doc_id, n_tokens, n_known, base_score, score) of every row; one narrow pass over the mapped trie."""
    ship(docs.sparkSession)
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return picked.mapInArrow(lambda it: _score(it, layout), "doc_id long, n_tokens long, n_known long, base_score double, score double")


def held_out_scores(docs: DataFrame, folds: int = 10, least: int = 1, **sizes: int) -> DataFrame:
    """Train on the rows outside the held-out fold and score all rows.

    Null texts are empty: one end token. Rows with a null doc_id train and are not held out; repeated
    rows count and are scored each. Without training texts every word has the same smoothed frequency.
    """
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds == 0, F.lit(False))
    layout = train(docs.where(~held).select("text"), least, **sizes)
    return score(docs, layout).select(
        "doc_id", held.alias("held_out"), "n_tokens", "n_known", F.lit(layout.total).cast("long").alias("train_tokens"), "base_score", "score"
    )
