"""SentencePiece merge-type (BPE) encoding and decoding in time linear in the text.

For every prefix of a string there is exactly one last token of its encoding. The encoder walks an
automaton over all pieces; at each position the pieces that end there are tried, longest first, and
the one that may stand after the last token of the prefix before it is the prefix's last token. Two
tokens may stand side by side if merging their characters in rank order never joins across their
border; verdicts are remembered. Ids are then read off backwards from the end of the string.

A text is cut where no piece holds the two neighbouring characters, which cannot change the result;
equal fragments of a slice of rows are encoded once. Runs of spaces, whose pieces all have one score
and so have no rank order, are merged by replaying the queue of merges once per run length.
"""

from __future__ import annotations

import hashlib
import heapq
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .runtime import bound_batches, ship

SPACE = "▁"
#: Fragments whose ids a worker remembers, at most; the table is emptied when it is full (some 15 MB).
REMEMBERED = 1 << 16
#: Pairs of tokens whose verdict a worker remembers, likewise.
REMEMBERED_PAIRS = 1 << 17
_NEVER = 1 << 60


def replay(symbols: list[str], score: dict[str, float]) -> tuple[list[str], dict[str, tuple[str, str]]]:
    """Merge neighbours by best score, leftmost first; (what is left, each product's two parts)."""
    left = list(range(-1, len(symbols) - 1))
    right = [*range(1, len(symbols)), -1]
    alive = list(symbols)
    parts: dict[str, tuple[str, str]] = {}
    queue: list[tuple[float, int, int, str]] = []

    def offer(i: int, j: int) -> None:
        if i >= 0 and j >= 0 and (both := alive[i] + alive[j]) in score:
            heapq.heappush(queue, (-score[both], i, j, both))

    for i in range(len(symbols) - 1):
        offer(i, i + 1)
    while queue:
        _, i, j, both = heapq.heappop(queue)
        if not alive[i] or not alive[j] or right[i] != j or alive[i] + alive[j] != both:
            continue
        parts[both] = (alive[i], alive[j])
        alive[i], alive[j] = both, ""
        right[i] = right[j]
        if right[j] >= 0:
            left[right[j]] = i
        offer(left[i], i)
        offer(i, right[i])
    return [s for s in alive if s], parts


@dataclass
class Pieces:
    """A vocabulary: (piece, score, kind) by id; kind: normal, byte, control, unknown or unused."""

    pieces: list[tuple[str, float, str]]
    dummy_prefix: bool = True
    bos: int = 1
    eos: int = 2
    ids: dict[str, int] = field(init=False, repr=False)

    def __post_init__(self) -> None:
        self.ids = {p: i for i, (p, _, kind) in enumerate(self.pieces) if kind == "normal"}
        self.bytes_at = {int(p[3:5], 16): i for i, (p, _, kind) in enumerate(self.pieces) if kind == "byte"}
        self.unknown = next(i for i, x in enumerate(self.pieces) if x[2] == "unknown")
        self.runs = {p: s for p, s, kind in self.pieces if kind == "normal" and len(p) > 1 and set(p) == {SPACE}}
        if any(SPACE in p.lstrip(SPACE) or p.startswith(SPACE * 2) for p in self.ids if p not in self.runs):
            raise ValueError("a piece has a space behind its first character: fragments can't be cut at spaces")
        self._rank_pieces()
        self._automaton()
        self._cuts()
        table = [b"" if kind == "control" else bytes([int(p[3:5], 16)]) if kind == "byte" else " ⁇ ".encode() if kind == "unknown" else p.replace(SPACE, " ").encode() for p, _, kind in self.pieces]
        self.body = np.frombuffer(b"".join(table), np.uint8)
        self.length = np.fromiter(map(len, table), np.int64, len(table))
        self.begin = np.cumsum(self.length) - self.length
        self.memo: dict[bytes, tuple[int, ...]] = {}
        self.beside: dict[int, bool] = {}
        self.run_ids: dict[int, tuple[int, ...]] = {}

    def _rank_pieces(self) -> None:
        score = {p: self.pieces[i][1] for p, i in self.ids.items() if p not in self.runs and len(p) > 1}
        order = sorted(set(score.values()), reverse=True)
        at = {s: r for r, s in enumerate(order)}
        self.rank: dict[str, int] = {p: at[s] for p, s in score.items()}
        self.parts: dict[str, tuple[str, str]] = {}
        for p in score:
            whole, parts = replay(list(p), score)
            if len(whole) == 1:
                self.parts[p] = parts[p]
        for p, (a, b) in self.parts.items():
            if max(self.rank.get(a, -1), self.rank.get(b, -1)) >= self.rank[p]:
                raise ValueError(f"piece {p!r} outranks its parts: prefixes have no rank order")
        self.spines: dict[tuple[str, bool], list[str]] = {}

    def _spine(self, piece: str, last: bool) -> list[str]:
        """From the border's character up to the piece, the symbols that stand at one border of it."""
        if (got := self.spines.get((piece, last))) is None:
            got = [piece]
            while (two := self.parts.get(got[-1])) is not None:
                got.append(two[last])
            got.reverse()
            self.spines[piece, last] = got
        return got

    def may_follow(self, a: str, b: str) -> bool:
        """Whether merging the characters of a and b leaves exactly these two."""
        left, right = self._spine(a, True), self._spine(b, False)
        i = j = 0
        while True:
            grow_left = self.rank[left[i + 1]] if i + 1 < len(left) else _NEVER
            grow_right = self.rank[right[j + 1]] if j + 1 < len(right) else _NEVER
            across = self.rank.get(left[i] + right[j], _NEVER)
            if across < grow_left and across <= grow_right and across != _NEVER:
                return False
            if grow_left == grow_right == _NEVER:
                return True
            if grow_left <= grow_right:
                i += 1
            else:
                j += 1

    def _automaton(self) -> None:
        """Goto and failure links over the reachable pieces; per state the pieces that end there, longest first."""
        go: list[dict[str, int]] = [{}]
        ends: list[tuple[int, ...]] = [()]
        for p, i in self.ids.items():
            if p in self.runs or (len(p) > 1 and p not in self.parts):
                continue
            state = 0
            for c in p:
                if (to := go[state].get(c)) is None:
                    to = go[state][c] = len(go)
                    go.append({})
                    ends.append(())
                state = to
            ends[state] = (i,)
        fail = [0] * len(go)
        level = list(go[0].values())
        while level:
            below = []
            for state in level:
                for c, to in go[state].items():
                    f = fail[state]
                    while f and c not in go[f]:
                        f = fail[f]
                    fail[to] = go[f].get(c, 0)
                    ends[to] += ends[fail[to]]
                    below.append(to)
            level = below
        self.go, self.fail, self.ends = go, fail, ends
        self.chars = [len(p) for p, _, _ in self.pieces]

    def _cuts(self) -> None:
        joined = np.zeros((256, 256), bool)
        byte = lambda c: 0x20 if c == SPACE else min(ord(c), 128)  # noqa: E731  128: any byte of a longer character
        pairs = {(byte(a), byte(b)) for p in self.ids for a, b in zip(p, p[1:])}
        for a, b in pairs:
            joined[a if a < 128 else slice(128, None), b if b < 128 else slice(128, None)] = True
        joined[128:, 128:] = True
        self.cut = ~joined

    def prefix_tokens(self, text: str) -> list[int]:
        """The last token of every prefix (by characters); -1 where it is a character without a piece."""
        go, fail, ends, chars, beside, names = self.go, self.fail, self.ends, self.chars, self.beside, self.pieces
        last: list[int] = []
        state = 0
        for p, c in enumerate(text, 1):
            while (to := go[state].get(c)) is None and state:
                state = fail[state]
            state = to or 0
            found = -1
            for t in ends[state]:
                q = p - chars[t]
                before = last[q - 1] if q else -1
                if before < 0:
                    found = t
                    break
                key = before << 20 | t
                if (good := beside.get(key)) is None:
                    if len(beside) >= REMEMBERED_PAIRS:
                        beside.clear()
                    good = beside[key] = self.may_follow(names[before][0], names[t][0])
                if good:
                    found = t
                    break
            last.append(found)
        return last

    def _word(self, text: str) -> list[int]:
        last = self.prefix_tokens(text)
        out: list[int] = []
        p = len(text)
        while p:
            t = last[p - 1]
            if t >= 0:
                out.append(t)
                p -= self.chars[t]
            else:
                p -= 1
                raw = text[p].encode()
                out.extend(reversed([self.bytes_at[b] for b in raw]) if self.bytes_at else [self.unknown])
        out.reverse()
        return out

    def _run(self, n: int) -> tuple[int, ...]:
        if (got := self.run_ids.get(n)) is None:
            got = tuple(self.ids[s] for s in replay([SPACE] * n, self.runs)[0])
            if len(self.run_ids) < 10_000:
                self.run_ids[n] = got
        return got

    def fragment(self, raw: bytes) -> tuple[int, ...]:
        """Ids of a fragment: spaces, then characters without spaces."""
        if (got := self.memo.get(raw)) is None:
            rest = raw.lstrip(b" ")
            spaces = len(raw) - len(rest)
            if not rest:
                got = self._run(spaces)
            elif not spaces:
                got = tuple(self._word(rest.decode()))
            else:
                word = self._word(SPACE + rest.decode())
                if word[0] == self.ids.get(SPACE):
                    got = (*self._run(spaces), *word[1:])
                else:
                    got = (*(self._run(spaces - 1) if spaces > 1 else ()), *word)
            if len(self.memo) >= REMEMBERED:
                self.memo.clear()
            self.memo[raw] = got
        return got

    def encode_rows(self, body: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all rows one after the other, number per row), without begin and end ids."""
        rows = len(offsets) - 1
        full = np.diff(offsets) > 0
        if self.dummy_prefix:
            grown = offsets + np.concatenate([[0], np.cumsum(full)])
            text = np.full(int(grown[-1]), 0x20, np.uint8)
            text[K.spread(grown[:-1][full] + 1, np.diff(offsets)[full])] = body
            body, offsets = text, grown
        if not len(body):
            return np.zeros(0, np.uint32), np.zeros(rows, np.int64)
        fresh = np.empty(len(body), bool)
        fresh[0] = True
        fresh[1:] = self.cut[body[:-1], body[1:]]
        fresh[offsets[:-1][full]] = True
        start = np.flatnonzero(fresh)
        # fragments lie end to end: equal ones, byte by byte, are encoded once
        edges = np.append(start, len(body)).astype(np.int64)
        spans = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(start), [None, pa.py_buffer(edges), pa.py_buffer(np.ascontiguousarray(body))])
        coded = spans.dictionary_encode()
        which = coded.indices.to_numpy()
        found = [self.fragment(x) for x in coded.dictionary.to_pylist()]
        size = np.fromiter(map(len, found), np.int64, len(found))
        flat = np.fromiter((i for ids in found for i in ids), np.uint32, int(size.sum()))
        begin = np.cumsum(size) - size
        ids = flat[K.spread(begin[which], size[which])]
        per = np.diff(np.concatenate([[0], np.cumsum(size[which])])[np.searchsorted(start, offsets)])
        return ids, per

    def decode_rows(self, ids: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(UTF-8 bytes, offsets) of rows of ids that encode_rows gave; the leading space goes."""
        size = self.length[ids]
        out = self.body[K.spread(self.begin[ids], size)]
        offsets = np.concatenate([[0], np.cumsum(size)])[np.concatenate([[0], np.cumsum(counts)])]
        return out, offsets

    def encode(self, text: str | None, begin_end: bool = False) -> list[int]:
        raw = np.frombuffer((text or "").replace(SPACE, " ").encode(), np.uint8)
        ids = self.encode_rows(raw, np.array([0, len(raw)]))[0].tolist()
        return [self.bos, *ids, self.eos] if begin_end else ids

    def decode(self, ids: list[int]) -> str:
        """The text of any ids: control ids vanish, byte ids join to UTF-8 (each byte that fits nowhere
        becomes U+FFFD), the space before the first piece goes."""
        out: list[str] = []
        held = bytearray()
        started = False

        def release() -> None:
            i = 0
            while i < len(held):
                for n in (1, 2, 3, 4):
                    try:
                        out.append(held[i : i + n].decode())
                        i += n
                        break
                    except UnicodeDecodeError:
                        continue
                else:
                    out.append("�")
                    i += 1
            held.clear()

        for i in ids:
            piece, _, kind = self.pieces[i]
            if kind == "byte":
                held.append(int(piece[3:5], 16))
                started = True
                continue
            release()
            if kind == "control":
                continue
            text = " ⁇ " if kind == "unknown" else piece.replace(SPACE, " ")
            if not started and self.dummy_prefix and kind != "unknown" and text.startswith(" "):
                text = text[1:]
            started = True
            out.append(text)
        release()
        return "".join(out)


def load_pieces(model_file: str) -> Pieces:
    """Read a model file on the driver; the tables travel to the executors."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
    kind = lambda i: "byte" if sp.is_byte(i) else "control" if sp.is_control(i) else "unknown" if sp.is_unknown(i) else "unused" if sp.is_unused(i) else "normal"
    return Pieces([(sp.id_to_piece(i), sp.get_score(i), kind(i)) for i in range(sp.vocab_size())], True, sp.bos_id(), sp.eos_id())


def _digests(batches: Iterator[pa.RecordBatch], shared, with_ids: bool) -> Iterator[pa.RecordBatch]:
    table: Pieces = shared.value
    begin, end = np.array([table.bos], "<u4").tobytes(), np.array([table.eos], "<u4").tobytes()
    for batch in batches:
        text = pc.replace_substring(batch.column(1).cast(pa.large_string()), SPACE, " ")
        batch = pa.RecordBatch.from_arrays([batch.column(0), text], names=["doc_id", "text"])
        for i, j, body, offsets in K.slices(batch, "text"):
            ids, counts = table.encode_rows(body, offsets)
            raw = memoryview(ids.astype("<u4").tobytes())
            ends = np.concatenate([[0], np.cumsum(counts)])
            out, where = table.decode_rows(ids, counts)
            shown = memoryview(out.tobytes())
            spans = list(zip(ends[:-1].tolist(), ends[1:].tolist()))
            first, last = where[:-1].tolist(), where[1:].tolist()
            hashes, decoded, starts = [], [], []
            for (a, b), c, d in zip(spans, first, last):
                h = hashlib.sha256(begin)
                h.update(raw[4 * a : 4 * b])
                h.update(end)
                hashes.append(h.hexdigest())
                c += c < d and shown[c] == 0x20
                starts.append(c)
                decoded.append(hashlib.sha256(shown[c:d]).hexdigest())
            columns = [batch.column(0).slice(i, j - i), pa.array(counts + 2), pa.array(hashes), pa.array(decoded)]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if with_ids:
                columns += [
                    pa.array([[table.bos, *ids[a:b].tolist(), table.eos] for a, b in spans], pa.list_(pa.int32())),
                    pa.array([bytes(shown[c:d]).decode() for c, d in zip(starts, last)]),
                ]
                names += ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays(columns, names=names)


def encode_decode(docs: DataFrame, model_file: str, with_ids: bool = False) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256[, ids, decoded]) of every row; one narrow pass.

    Null texts count as empty (begin and end id only). Repeated rows and null doc_ids come back as they
    came; further columns are ignored.
    """
    spark = docs.sparkSession
    ship(spark)
    bound_batches(spark)
    shared = spark.sparkContext.broadcast(load_pieces(model_file))
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * with_ids
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return picked.mapInArrow(lambda it: _digests(it, shared, with_ids), schema)
