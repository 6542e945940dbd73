"""Byte-level BPE encoding and decoding with a vectorised pre-tokeniser.

A batch of texts becomes one array of codepoint classes. Each class is a transition function over the states
of a small automaton; these functions are closed under composition, so prefix states come from an associative
scan: blocks of the array are scanned side by side, block totals are scanned once more, and each position's
state is its block's entry state sent through its local prefix. States and classes of a position and its
neighbours then say where a token starts; no regular expression runs. The slices between starts meet a cache
of merged pairs, and the ids of a text stay together with the byte offset at which each one decodes.

The split is that of the public pattern ``PATTERN`` of the tokenizer files: contractions, letters, numbers
and other runs with an optional leading blank, and white space that leaves its last character to what follows.

Defined results: a null text is empty and has no tokens; texts of any length are split whole, a batch being
cut between texts only; repeated rows repeat their results; further columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import unicodedata
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import require_columns

# Codepoint classes.
SEP, BLANK, SPACE, NUM, OTHER, APOS, LET, L_STMD, L_R, L_V, L_L, L_E = range(12)
# States: what the character at a position turned out to be.
(S_SEP, S_BLANK, S_SPACE, S_NUM, S_OTHER, S_APOS, S_LET, S_ONE, S_R, S_V, S_L, S_TWO) = range(12)
STATES = 12

#: The code points with the White_Space property.
WHITE_SPACE = [9, 10, 11, 12, 13, 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
#: Letters and numbers assigned after the character database of this Python.
LATER_LETTERS = [(0x1C89, 0x1C8A), (0xA7CB, 0xA7CD), (0xA7DA, 0xA7DC), (0x105C0, 0x105F3), (0x10D4A, 0x10D65), (0x10D6F, 0x10D85), (0x10EC2, 0x10EC4), (0x11380, 0x11389), (0x1138B, 0x1138B), (0x1138E, 0x1138E), (0x11390, 0x113B5), (0x113B7, 0x113B7), (0x113D1, 0x113D1), (0x113D3, 0x113D3), (0x11BC0, 0x11BE0), (0x13460, 0x143FA), (0x16100, 0x1611D), (0x16D40, 0x16D6C), (0x1E5D0, 0x1E5ED), (0x1E5F0, 0x1E5F0)]
LATER_NUMBERS = [(0x10D40, 0x10D49), (0x116D0, 0x116E3), (0x11BF0, 0x11BF9), (0x16130, 0x16139), (0x16D70, 0x16D79), (0x1CCF0, 0x1CCF9), (0x1E5F1, 0x1E5FA)]
SENTINEL = "\ud800"  # a lone surrogate, which no stored text can hold


@lru_cache(maxsize=1)
def class_table() -> np.ndarray:
    """Class of each code point; letters and numbers by general category."""
    table = np.full(0x110000, OTHER, dtype=np.uint8)
    for cp in range(0x110000):
        c = unicodedata.category(chr(cp))[0]
        if c == "L":
            table[cp] = LET
        elif c == "N":
            table[cp] = NUM
    for ranges, cls in ((LATER_LETTERS, LET), (LATER_NUMBERS, NUM)):
        for a, z in ranges:
            table[a : z + 1] = cls
    table[WHITE_SPACE] = SPACE
    table[ord(" ")] = BLANK
    table[ord("'")] = APOS
    for chars, cls in (("stmd", L_STMD), ("r", L_R), ("v", L_V), ("l", L_L), ("e", L_E)):
        for ch in chars:
            table[ord(ch)] = cls
    table[ord(SENTINEL)] = SEP
    return table


def _step(state: int, cls: int) -> int:
    if cls <= OTHER:
        return cls
    if cls == APOS:  # joins a run of others or a leading blank, else it may open a contraction
        return S_OTHER if state in (S_OTHER, S_APOS, S_BLANK) else S_APOS
    if state == S_APOS:
        return {L_STMD: S_ONE, L_R: S_R, L_V: S_V, L_L: S_L}.get(cls, S_LET)
    if (state in (S_R, S_V) and cls == L_E) or (state == S_L and cls == L_L):
        return S_TWO
    return S_LET


@lru_cache(maxsize=1)
def transition_monoid() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(functions[f, state], compose[f * n + g] = first f then g, element of each class)."""
    gens = [tuple(_step(s, c) for s in range(STATES)) for c in range(STATES)]
    found = {g: i for i, g in enumerate(dict.fromkeys(gens))}
    queue = list(found)
    while queue:
        f = queue.pop()
        for g in gens:
            h = tuple(g[x] for x in f)
            if h not in found:
                found[h] = len(found)
                queue.append(h)
    functions = np.array(list(found), dtype=np.uint8)
    n = len(found)
    compose = np.empty((n, n), dtype=np.uint16)
    for i, f in enumerate(found):
        for j, g in enumerate(found):
            compose[i, j] = found[tuple(g[x] for x in f)]
    return functions, compose.ravel(), np.array([found[g] for g in gens], dtype=np.uint16)


def scan_states(classes: np.ndarray, block: int = 256) -> np.ndarray:
    """State of every position, starting from S_SEP: an associative scan over the classes' functions."""
    functions, compose, element = transition_monoid()
    n, size = len(classes), np.intp(len(functions))
    cols = -(-n // block)
    padded = np.zeros(cols * block, dtype=np.uint16)
    padded[:n] = element[classes]
    lanes = np.ascontiguousarray(padded.reshape(cols, block).T)  # lanes[j]: the j-th position of every block
    for j in range(1, block):
        lanes[j] = compose[lanes[j - 1].astype(np.intp) * size + lanes[j]]
    entry = np.empty(cols, dtype=np.uint8)
    state, totals = S_SEP, functions[lanes[-1]]
    for b in range(cols):
        entry[b] = state
        state = totals[b, state]
    return functions[lanes, entry[None, :]].T.ravel()[:n]


def token_starts(classes: np.ndarray) -> np.ndarray:
    """Positions where a token or a separator begins. classes must begin and end with SEP."""
    s = scan_states(classes)
    prev, nxt = np.empty_like(s), np.empty_like(s)
    prev[0], prev[1:] = S_SEP, s[:-1]
    nxt[-1], nxt[:-1] = S_SEP, s[1:]
    white = (s == S_BLANK) | (s == S_SPACE)
    prev_white = (prev == S_BLANK) | (prev == S_SPACE)
    next_solid = (nxt != S_BLANK) & (nxt != S_SPACE) & (nxt != S_SEP)
    other, prev_other = (s == S_OTHER) | (s == S_APOS), (prev == S_OTHER) | (prev == S_APOS)
    letter = s >= S_LET
    prev_run = (prev >= S_LET) & (prev != S_ONE) & (prev != S_TWO)
    contraction = (prev == S_APOS) & ((s == S_ONE) | (nxt == S_TWO) & (s >= S_R) & (s <= S_L))
    joined = white & prev_white & ~next_solid
    joined |= ~white & (s != S_SEP) & (prev == S_BLANK)
    joined |= other & prev_other
    joined |= (s == S_NUM) & (prev == S_NUM)
    joined |= letter & (prev_run | contraction)
    return np.flatnonzero(~joined)


class Merges:
    """Pair merging over a rank table: the adjacent pair of the lowest rank merges first, leftmost among equals."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks, self.pair = ranks, {}
        for piece, r in ranks.items():
            for cut in range(1, len(piece)):
                if (a := ranks.get(piece[:cut])) is not None and (b := ranks.get(piece[cut:])) is not None:
                    self.pair[a << 32 | b] = r
        self.single = [ranks[bytes([b])] for b in range(256)]

    def __call__(self, piece: bytes) -> list[int]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        return self._short(piece) if len(piece) <= 256 else self._long(piece)

    def _short(self, piece: bytes) -> list[int]:
        find, none = self.pair.get, 1 << 62
        ids = [self.single[b] for b in piece]
        open_ = [find(a << 32 | b, none) for a, b in zip(ids, ids[1:])]
        while open_ and (r := min(open_)) != none:
            i = open_.index(r)
            ids[i : i + 2] = [r]
            del open_[i]
            if i:
                open_[i - 1] = find(ids[i - 1] << 32 | r, none)
            if i < len(open_):
                open_[i] = find(r << 32 | ids[i + 1], none)
        return ids

    def _long(self, piece: bytes) -> list[int]:
        """The same with a heap and a linked list, for runs of thousands of bytes."""
        find, n = self.pair.get, len(piece)
        ids, right, left = [self.single[b] for b in piece], list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := find(ids[i] << 32 | ids[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            r, i, a, b = heapq.heappop(heap)
            j = right[i]
            if ids[i] != a or j >= n or ids[j] != b:
                continue
            ids[i], ids[j], right[i] = r, -1, right[j]
            if right[i] < n:
                left[right[i]] = i
            for x, y in ((left[i], i), (i, right[i])):
                if x >= 0 and y < n and (q := find(ids[x] << 32 | ids[y])) is not None:
                    heapq.heappush(heap, (q, x, ids[x], ids[y]))
        return [x for x in ids if x >= 0]


class _Merged(dict):
    """slice -> its ids as packed little-endian 32-bit words; bounded by emptying."""

    def __init__(self, ranks: dict[bytes, int], limit: int):
        super().__init__()
        self.merges, self.limit = Merges(ranks), limit

    def __missing__(self, piece: str) -> bytes:
        ids = np.array(self.merges(piece.encode()), dtype="<u4").tobytes()
        if len(piece) <= 64:
            if len(self) >= self.limit:
                self.clear()
            self[piece] = ids
        return ids


class Codec:
    """Encoder and decoder over a rank file (lines of base64 bytes and rank)."""

    def __init__(self, path: str, cache: int = 600_000):
        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.merged = _Merged(ranks, cache)
        vocab = [b""] * (max(ranks.values()) + 1)
        for piece, r in ranks.items():
            vocab[r] = piece
        self.lengths = np.array([len(v) for v in vocab], dtype=np.int64)
        self.firsts = np.concatenate([[0], np.cumsum(self.lengths)[:-1]])
        self.bytes = np.frombuffer(b"".join(vocab), dtype=np.uint8)

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text."""
        joined = SENTINEL + SENTINEL.join(texts) + SENTINEL
        points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        classes = class_table()[points]
        starts = token_starts(classes)
        marks = np.flatnonzero(classes[starts] == SEP)
        edges = starts.tolist()
        look, out = self.merged.__getitem__, []
        for a, z in zip(marks[:-1].tolist(), marks[1:].tolist()):
            spans = edges[a + 1 : z + 1]
            out.append(np.frombuffer(b"".join([look(joined[i:j]) for i, j in zip(spans, spans[1:])]), dtype="<u4"))
        return out

    def offsets(self, ids: np.ndarray) -> np.ndarray:
        """Byte offset of each id in the decoded text, and the end."""
        return np.concatenate([[0], np.cumsum(self.lengths[ids])])

    def decode(self, ids: np.ndarray) -> bytes:
        at, n = self.offsets(ids), self.lengths[ids]
        shift = np.repeat(self.firsts[ids] - at[:-1], n)
        return self.bytes[shift + np.arange(at[-1])].tobytes()


@lru_cache(maxsize=4)
def codec(path: str) -> Codec:
    return Codec(path)


def text_chunks(texts: list[str], limit: int = 1 << 20):
    """Runs of whole texts of about ``limit`` characters."""
    first, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > limit:
            yield first, i
            first, size = i, 0
        size += len(t)
    if first < len(texts):
        yield first, len(texts)


def encode_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, ids (array<int>) and the byte offsets of the tokens (array<long>) for every row."""
    require_columns(docs, id_col, text_col)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        tool = codec(path)
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            for a, z in text_chunks(texts):
                ids = tool.encode(texts[a:z])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, z - a), pa.array([x.astype(np.int32) for x in ids], pa.list_(pa.int32())), pa.array([tool.offsets(x) for x in ids], pa.list_(pa.int64()))], [id_col, "ids", "offsets"])

    return docs.select(id_col, F.col(text_col).cast("string")).mapInArrow(run, f"`{id_col}` {kind}, ids array<int>, offsets array<bigint>")


def decode_documents(encoded: DataFrame, path: str, id_col: str = "doc_id") -> DataFrame:
    kind = encoded.schema[id_col].dataType.simpleString()

    def run(batches):
        tool = codec(path)
        for batch in batches:
            data = [tool.decode(np.asarray(x or [], dtype=np.int64)) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(data, pa.binary())], [id_col, "data"])

    return encoded.select(id_col, "ids").mapInArrow(run, f"`{id_col}` {kind}, data binary")


def encoding_report(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256; ids are decoded where they were made and do not travel."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        tool = codec(path)
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            for a, z in text_chunks(texts):
                n, ids_hash, text_hash = [], [], []
                for ids in tool.encode(texts[a:z]):
                    n.append(len(ids))
                    ids_hash.append(hashlib.sha256(ids.tobytes()).hexdigest())
                    text_hash.append(hashlib.sha256(tool.decode(ids)).hexdigest())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, z - a), pa.array(n, pa.int64()), pa.array(ids_hash, pa.string()), pa.array(text_hash, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
