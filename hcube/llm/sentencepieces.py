"""SentencePiece encoding by suffix-array matching, and decoding.

A batch's texts are normalised (spaces become U+2581, one goes in front) and cut where
no piece can reach across: before a run of U+2581 and around line ends.  The distinct
units that are not known yet are laid end to end; a suffix array of that text, ordered
to the depth of the longest piece, gives every piece's occurrences as one range by
binary search.  The ranges become edges (position, length, piece), ordered by
position; relaxing them is joining the neighbours of best score first (byte-pair
models) or the best path of scores (unigram models).  What no piece covers falls back
to byte pieces.  Known units stay with the worker up to a bound, so frequent words are
matched once.

Defined results: null texts count as empty; empty texts have no ids; rows are encoded
one by one, so repeated rows give equal results and a null doc_id keeps its row; very
long texts, and ones without any space, are encoded whole; of equal scores the leftmost
pair goes first; an empty table gives no rows; columns other than doc_id and text are not read.
"""

from __future__ import annotations

import functools
import heapq
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPACE = "▁"
MODEL = "piece_bpe_32k.model"
KNOWN_UNITS = 600_000
BATCH_CHARS = 4_000_000
LONG_UNIT = 256
_UNIT = re.compile(f"\n|{SPACE}*[^{SPACE}\n]+|{SPACE}+")


class Pieces:
    """A vocabulary: texts, scores and kinds of its pieces."""

    def __init__(self, texts: list[str], scores: list[float], byte_ids: list[int | None], unknown: int = 0, kind: str = "bpe"):
        self.kind, self.unknown = kind, unknown
        self.match = [(i, t) for i, t in enumerate(texts) if t]
        self.byte_ids = byte_ids
        self.score = np.array(scores)
        # Rank by score: equal scores share a rank, so the leftmost of them goes first.
        self.rank = np.unique(-self.score, return_inverse=True)[1].astype(np.int64)
        self.longest = max([1, *(len(t) for _, t in self.match)])
        self.alphabet = sorted({c for _, t in self.match for c in t})
        plain = {i: t.replace(SPACE, " ").encode() for i, t in self.match}
        plain |= {i: bytes([b]) for b, i in enumerate(byte_ids) if i is not None}
        parts = [plain.get(i, b"") for i in range(len(texts))]
        self.byte_len = np.array([len(p) for p in parts], np.int64)
        self.byte_at = np.cumsum(self.byte_len) - self.byte_len
        self.blob = np.frombuffer(b"".join(parts), np.uint8)

    @classmethod
    def load(cls, name: str = MODEL) -> Pieces:
        import public_tokenizers
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(name))
        n = sp.vocab_size()
        special = [sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i) for i in range(n)]
        by_byte = {sp.id_to_piece(i): i for i in range(n) if sp.is_byte(i)}
        return cls(
            ["" if s else sp.id_to_piece(i) for i, s in enumerate(special)], [sp.get_score(i) for i in range(n)],
            [by_byte.get(f"<0x{b:02X}>") for b in range(256)], sp.unk_id(),
        )


def ragged(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Indices of all the runs ``starts[i] : starts[i] + lens[i]``, end to end."""
    return np.repeat(starts - np.cumsum(lens) + lens, lens) + np.arange(lens.sum())


def _codes(chars: np.ndarray, pieces: Pieces) -> tuple[np.ndarray, dict[str, int], int]:
    """Characters as small codes in order; 0 pads, 1 is any that no piece has; bits of a code."""
    alphabet = np.array([ord(c) for c in pieces.alphabet], np.int64)
    present = np.intersect1d(np.unique(chars), alphabet)
    bits = 8 if len(present) < 254 else 16
    at = np.minimum(np.searchsorted(present, chars), max(len(present) - 1, 0))
    codes = np.where(present[at] == chars, at + 2, 1) if len(present) else np.ones(len(chars), np.int64)
    return codes.astype(np.uint64), {chr(c): k + 2 for k, c in enumerate(present.tolist())}, bits


def edges(units: list[str], pieces: Pieces) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """All occurrences of pieces in the units: position, length, piece; and each unit's start.

    Positions count characters of the units laid end to end, one separator after each.
    """
    text = "\n\n".join(["", *units, ""])[2:]  # two separators keep the arithmetic of starts plain
    chars = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    lens = np.fromiter(map(len, units), np.int64, len(units))
    starts = np.cumsum(lens + 2) - lens - 2
    codes, code_of, bits = _codes(chars, pieces)
    codes[(starts + lens)[:, None] + np.arange(2)] = 0  # no piece crosses a separator
    per = 64 // bits
    n_words = -(-pieces.longest // per)
    # Each suffix's first characters as big-endian words: order of words is order of suffixes.
    padded = np.r_[codes, np.zeros(per * n_words + 1, np.uint64)]
    n = len(codes)
    word = np.zeros(len(padded), np.uint64)
    for k in range(per):
        word[: len(padded) - k] |= padded[k:] << np.uint64(64 - bits * (k + 1))
    keys = [word[k * per : k * per + n] for k in range(n_words)]
    suffixes = np.lexsort(keys[::-1])
    keys = [k[suffixes] for k in keys]
    # Binary search of every piece whose characters all occur.
    some = [(i, t) for i, t in pieces.match if all(c in code_of for c in t)]
    ids = np.array([i for i, _ in some], np.int64)
    size = np.array([len(t) for _, t in some], np.int64)
    table = np.zeros((len(some), per * n_words), np.uint64)
    for row, (_, t) in enumerate(some):
        table[row, : len(t)] = [code_of[c] for c in t]
    full = np.uint64(2**bits - 1)
    lo, hi = np.zeros(len(some), np.int64), np.full(len(some), n, np.int64)
    shifts = np.uint64(64) - np.uint64(bits) * (np.arange(per, dtype=np.uint64) + np.uint64(1))
    for k in range(n_words):
        block = table[:, k * per : (k + 1) * per]
        inside = np.arange(k * per, (k + 1) * per)[None, :] < size[:, None]
        low = (block << shifts).sum(1, dtype=np.uint64)
        high = (np.where(inside, block, full) << shifts).sum(1, dtype=np.uint64)
        on = size > k * per
        if k == 0:
            lo, hi = np.searchsorted(keys[0], low, "left"), np.searchsorted(keys[0], high, "right")
        else:
            lo[on], hi[on] = (_within(keys[k], lo[on], hi[on], v, side) for v, side in ((low[on], "left"), (high[on], "right")))
    found = np.maximum(hi - lo, 0)
    pos = suffixes[ragged(lo, found)]
    which = np.repeat(np.arange(len(some)), found)
    order = np.argsort(pos, kind="stable")
    return pos[order], size[which][order], ids[which][order], starts


def _within(keys: np.ndarray, lo: np.ndarray, hi: np.ndarray, value: np.ndarray, side: str) -> np.ndarray:
    """searchsorted of each value in its own range of ``keys``."""
    lo, hi = lo.copy(), hi.copy()
    while (open_ := lo < hi).any():
        mid = (lo + hi) // 2
        probe = keys[np.minimum(mid, len(keys) - 1)]
        right = open_ & ((probe < value) if side == "left" else (probe <= value))
        lo = np.where(right, mid + 1, lo)
        hi = np.where(open_ & ~right, mid, hi)
    return lo


def encode_units(units: list[str], pieces: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all units end to end, and how many each has."""
    if not units:
        return np.empty(0, np.int32), np.empty(0, np.int64)
    pos, size, piece, starts = edges(units, pieces)
    lens = np.fromiter(map(len, units), np.int64, len(units))
    relax = _join_best if pieces.kind == "bpe" else _best_path
    sym_at, sym_len, sym_unit, sym_id = relax(pos, size, piece, starts, lens, pieces)
    # Characters without a piece become the byte pieces of their UTF-8 form.
    bare = np.flatnonzero(sym_id < 0)
    count = np.ones(len(sym_id), np.int64)
    spelled: list[int] = []
    for k in bare.tolist():
        u = sym_unit[k]
        at = sym_at[k] - starts[u]
        ids = [pieces.byte_ids[b] for b in units[u][at : at + sym_len[k]].encode("utf-8", "surrogatepass")]
        ids = [pieces.unknown] if None in ids else ids
        count[k] = len(ids)
        spelled += ids
    out = np.repeat(sym_id, count)
    out[np.repeat(sym_id < 0, count)] = spelled
    return out.astype(np.int32), np.bincount(sym_unit, weights=count, minlength=len(units)).astype(np.int64)


def _join_best(pos, size, piece, starts, lens, pieces: Pieces):
    """Joins, unit by unit, the neighbouring symbols whose piece has the best score, leftmost first."""
    width = pieces.longest + 1
    base = np.int64(starts[-1] + lens[-1] + 2)
    of = np.full(base * width, -1, np.int32)  # by position and length: the edges, addressed
    of[pos * width + size] = piece
    # Rounds over all units join one pair of each; a long unit would need as many rounds as it has characters.
    short = lens <= LONG_UNIT
    done = [_join_long(int(starts[u]), int(lens[u]), int(u), of, width, pieces.rank) for u in np.flatnonzero(~short)]
    at = ragged(starts[short], lens[short])
    unit = np.repeat(np.flatnonzero(short), lens[short])
    length = np.ones(len(at), np.int64)
    none = np.int64(2**62)
    span = np.int64(1) << np.int64(34)
    while len(at):
        # Price of joining each symbol with the next: rank of the piece, then place.
        joined = length[:-1] + length[1:]
        fits = (unit[:-1] == unit[1:]) & (joined < width)
        target = np.where(fits, of[at[:-1] * width + np.minimum(joined, width - 1)], -1)
        price = np.full(len(at), none)
        price[:-1] = np.where(target >= 0, pieces.rank[np.maximum(target, 0)] * span + np.arange(len(at) - 1), none)
        head = np.flatnonzero(np.r_[True, unit[1:] != unit[:-1]])
        best = np.minimum.reduceat(price, head)
        live = best < none
        runs = np.diff(np.r_[head, len(at)])
        alive = np.repeat(live, runs)
        if not alive.all():  # units that are finished leave
            done.append((at[~alive], length[~alive], unit[~alive]))
        left = (best[live] & (span - 1)).astype(np.int64)
        length[left] += length[left + 1]
        alive[left + 1] = False
        at, length, unit = at[alive], length[alive], unit[alive]
    at, length, unit = map(np.concatenate, zip(*done)) if done else (at, length, unit)
    order = np.argsort(at, kind="stable")
    at, length, unit = at[order], length[order], unit[order]
    return at, length, unit, of[at * width + length].astype(np.int64)


def _join_long(start: int, n: int, unit: int, of: np.ndarray, width: int, rank: np.ndarray):
    """The same joins for one unit, by a queue of neighbouring pairs."""
    after, before, size = list(range(1, n + 1)), list(range(-1, n - 1)), [1] * n
    queue: list[tuple[int, int, int, int]] = []

    def offer(i: int) -> None:
        j = after[i]
        if j < n and size[i] + size[j] < width:
            piece = of[(start + i) * width + size[i] + size[j]]
            if piece >= 0:
                heapq.heappush(queue, (int(rank[piece]), i, size[i], size[j]))

    for i in range(n - 1):
        offer(i)
    while queue:
        _, i, a, b = heapq.heappop(queue)
        j = after[i]
        if size[i] != a or j >= n or size[j] != b:  # one of them was joined meanwhile
            continue
        size[i], size[j], after[i] = a + b, 0, after[j]
        if after[j] < n:
            before[after[j]] = i
        offer(i)
        if before[i] >= 0:
            offer(before[i])
    length = np.array(size, np.int64)
    kept = np.flatnonzero(length)
    return kept + start, length[kept], np.full(len(kept), unit, np.int64)


def _best_path(pos, size, piece, starts, lens, pieces: Pieces):
    """Path of pieces with the greatest sum of scores; a character without one costs more than any piece."""
    n = int(starts[-1] + lens[-1] + 2)
    floor = float(pieces.score.min()) - 10.0
    best = np.full(n + 1, -np.inf)
    best[starts] = 0.0
    came_len, came_id = np.ones(n + 1, np.int64), np.full(n + 1, -1, np.int64)
    offset = pos - starts[np.searchsorted(starts, pos, "right") - 1]
    order = np.argsort(offset + size, kind="stable")
    pos, size, piece, ends = pos[order], size[order], piece[order], (offset + size)[order]
    for k in range(1, int(lens.max(initial=0)) + 1):
        here = (starts + k)[lens >= k]
        best[here] = best[here - 1] + floor
        a, b = np.searchsorted(ends, k), np.searchsorted(ends, k, "right")
        p, s, i = pos[a:b], size[a:b], piece[a:b]
        total = best[p] + pieces.score[i]
        by = np.lexsort((-s, -total, p + s))
        first = by[np.r_[True, (p + s)[by][1:] != (p + s)[by][:-1]]] if len(by) else by
        better = first[total[first] > best[(p + s)[first]]]
        e = (p + s)[better]
        best[e], came_len[e], came_id[e] = total[better], s[better], i[better]
    out = []
    at, unit = starts + lens, np.arange(len(lens))
    while len(at):
        go = at > starts[unit]
        at, unit = at[go], unit[go]
        out.append((at - came_len[at], came_len[at], unit, came_id[at]))
        at = at - came_len[at]
    cols = [np.concatenate(c) for c in zip(*out)]
    order = np.argsort(cols[0], kind="stable")
    return tuple(c[order] for c in cols)


class Encoder:
    """Encodes batches of texts; keeps the ids of units it has met, up to a bound."""

    def __init__(self, pieces: Pieces, bound: int = KNOWN_UNITS):
        self.pieces, self.bound = pieces, bound
        self.clear()

    def clear(self) -> None:
        self.known: dict[str, int] = {}
        self.ids, self.lens, self.at = np.empty(0, np.int32), np.empty(0, np.int64), np.empty(0, np.int64)

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        if len(self.known) > self.bound:
            self.clear()
        known, before = self.known, len(self.known)
        number = lambda u: known.setdefault(u, len(known))
        rows = []
        for t in texts:
            units = _UNIT.findall(SPACE + t.replace(" ", SPACE)) if t else []
            rows.append(np.fromiter(map(number, units), np.int64, len(units)))
        if len(known) > before:
            fresh = list(known)[before:] if before else list(known)
            ids, lens = encode_units(fresh, self.pieces)
            self.ids, self.lens = np.r_[self.ids, ids], np.r_[self.lens, lens]
            self.at = np.cumsum(self.lens) - self.lens
        return [self.ids[ragged(self.at[r], self.lens[r])] if len(r) else np.empty(0, np.int32) for r in rows]

    def decode(self, ids: np.ndarray) -> bytes:
        """UTF-8 bytes of the text; the space put in front is taken off again."""
        p = self.pieces
        out = p.blob[ragged(p.byte_at[ids], p.byte_len[ids])].tobytes()
        return out[1:] if out.startswith(b" ") else out


@functools.lru_cache(maxsize=2)
def encoder(name: str = MODEL) -> Encoder:
    return Encoder(Pieces.load(name))


def encoded(docs: DataFrame, name: str = MODEL) -> DataFrame:
    """``(doc_id, ids array<int>)`` of the whole texts."""
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_run(name, False), "doc_id long, ids array<int>")


def _run(name: str, digest: bool):
    def batch_out(enc, doc_ids, texts):
        rows = enc.encode(texts)
        if not digest:
            return pa.RecordBatch.from_arrays([pa.array(doc_ids, pa.int64()), pa.array(rows, pa.list_(pa.int32()))], ["doc_id", "ids"])
        byte_ids = np.zeros(len(enc.pieces.byte_len), bool)
        byte_ids[[i for i in enc.pieces.byte_ids if i is not None]] = True
        back = [enc.decode(r) for r in rows]
        cols = [
            pa.array(doc_ids, pa.int64()), pa.array([len(r) for r in rows], pa.int64()),
            pa.array([zlib.crc32(r.astype("<u4").tobytes()) for r in rows], pa.int64()),
            pa.array([int(byte_ids[r].sum()) for r in rows], pa.int64()),
            pa.array([zlib.crc32(b) for b in back], pa.int64()),
            pa.array([b == t.encode() for b, t in zip(back, texts)], pa.bool_()),
        ]
        return pa.RecordBatch.from_arrays(cols, ["doc_id", "n_ids", "ids_crc32", "n_byte_ids", "decoded_crc32", "round_trip"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(name)
        ids, texts, size = [], [], 0
        for batch in batches:
            for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids.append(i)
                texts.append(t or "")
                size += len(texts[-1])
                if size >= BATCH_CHARS:
                    yield batch_out(enc, ids, texts)
                    ids, texts, size = [], [], 0
        if ids:
            yield batch_out(enc, ids, texts)

    return run


def decoded(rows: DataFrame, name: str = MODEL) -> DataFrame:
    """``(doc_id, text)`` from ``(doc_id, ids)``; bytes that are no UTF-8 become U+FFFD."""

    def run(batches):
        enc = encoder(name)
        for batch in batches:
            texts = [enc.decode(np.array(r or [], np.int64)).decode("utf-8", "replace") for r in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return rows.select(F.col("doc_id").cast("long"), "ids").mapInArrow(run, "doc_id long, text string")


def op10_sentencepiece(docs: DataFrame, name: str = MODEL) -> DataFrame:
    """Per document: ids and byte pieces counted, checksums of ids and of the decoded text."""
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(
        _run(name, True),
        "doc_id long, n_ids long, ids_crc32 long, n_byte_ids long, decoded_crc32 long, round_trip boolean",
    )
