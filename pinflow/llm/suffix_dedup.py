"""Removal of passages that an earlier document already holds, to the byte.

A byte goes if a ``SPAN``-byte string that covers it also starts in a document with a smaller id. Suffixes are
sorted only where that can matter:

1. Winnowing: each window of SPAN bytes selects the leftmost smallest hash of its GRAM-byte strings. Equal
   windows select equal grams, so windows can only be equal within the *segments* (runs of windows with one
   selected gram) of one gram.
2. Segments that agree whole are settled by their smallest document. Each task first settles what it holds
   itself, so a text that very many documents share leaves it once per task.
3. What is left, segments of one gram that differ somewhere, is ordered as suffixes: multikey quicksort to a
   shallow depth, then blind tries for the groups of long common prefixes. In that order windows that are equal to the
   depth of SPAN stand together, and get the smallest document of their run.
4. Grams with very many different segments are split further by the window's own hash.

Whole segments are settled in 2 by two independent 64-bit hashes, gram and segment, without their bytes; in 3 suffixes are
compared by their bytes.

Defined results: null texts are empty; texts under SPAN bytes stay whole; rows with a null id neither lose
bytes nor take any from others; rows that repeat an id are judged by id, so they never cut each other; an
empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import cut, discard, release, require_columns, shuffle_width, small_batches, trimmed
from .shingles import chunks as _chunks
from .shingles import mix

SPAN = 50
GRAM = 20
WIDE = SPAN - GRAM + 1
TASK_BYTES = 8 << 20
HELD = 250_000  # segments that a task gathers before it settles and ships them
CHUNK = 256 << 10  # bytes hashed at once
SHALLOW = 16  # bytes that multikey quicksort orders by
CROWD = 50_000  # different segments of one gram from which it is split
BLOB = np.dtype([("doc", "<i8"), ("print", "<u4"), ("ord", "<u4"), ("gram", "<u8"), ("segment", "<u8")])
MARK = np.dtype([("doc", "<i8"), ("print", "<u4"), ("ord", "<u4"), ("gram", "<u8"), ("state", "u1")])
COVERED, PARTIAL, CROWDED = 0, 1, 2


_BASE = np.uint64(0x9E3779B97F4A7C15)  # odd
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_VALUES = np.random.default_rng(20).integers(1, 1 << 63, 256, dtype=np.uint64)
_SECOND = np.random.default_rng(21).integers(1, 1 << 63, 256, dtype=np.uint64)  # the segment's hash is independent of its gram's
_powers: dict[str, np.ndarray] = {}


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers.get("up", ())) < n:
        size = max(n, 1 << 16)
        for name, base in (("up", _BASE), ("down", _INVERSE)):
            grown = np.full(size, base, dtype=np.uint64)
            grown[0] = 1
            _powers[name] = np.multiply.accumulate(grown)
    return _powers["up"], _powers["down"]


def chunks(texts: list[bytes]):
    return _chunks(texts, CHUNK)


def fingerprint(text: bytes) -> int:
    return int.from_bytes(hashlib.blake2b(text, digest_size=4).digest(), "little")


def segments(texts: list[bytes]):
    """All segments of the texts: (text index, ordinal in the text, first window, last window, gram hash, segment hash, data).

    Window positions count in ``data``, the texts' bytes one after another."""
    data = np.frombuffer(b"".join(texts), dtype=np.uint8)
    lengths = np.array([len(t) for t in texts], dtype=np.int64)
    ends = np.cumsum(lengths)
    windows = np.maximum(lengths - SPAN + 1, 0)
    if not windows.sum():
        none = np.empty(0, dtype=np.int64)
        return none, none, none, none, none.astype(np.uint64), none.astype(np.uint64), data
    n = len(data)
    up, down = _power(n + 1)
    total = np.empty(n + 1, dtype=np.uint64)
    total[0] = 0
    np.cumsum(_VALUES[data] * up[:n], out=total[1:])
    grams = mix((total[GRAM:] - total[:-GRAM]) * down[: n - GRAM + 1])
    least = (grams >> np.uint64(30) << np.uint64(30)) | np.arange(len(grams), dtype=np.uint64)
    step = 1
    while step * 2 <= WIDE:
        least = np.minimum(least[:-step], least[step:])
        step *= 2
    if step < WIDE:
        least = np.minimum(least[: -(WIDE - step)], least[WIDE - step :])
    starts = np.repeat(ends - lengths - (np.cumsum(windows) - windows), windows) + np.arange(windows.sum())
    anchor = (least[starts] & np.uint64((1 << 30) - 1)).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], anchor[1:] != anchor[:-1]]))
    last = np.concatenate([first[1:], [len(anchor)]]) - 1
    a, z, p = starts[first], starts[last], anchor[first]
    np.cumsum(_SECOND[data] * up[:n], out=total[1:])
    body = mix((total[z + SPAN] - total[a]) * down[a] + (z - a).astype(np.uint64) * np.uint64(0xA24BAED4963EE407) + (p - a).astype(np.uint64) * np.uint64(0x9FB21C651E98DF25))
    text = np.searchsorted(ends, a, side="right")
    opening = np.searchsorted(text, text, side="left")
    return text, np.arange(len(a)) - opening, a, z, grams[p], body, data


def settle(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sort segments by (gram, segment, doc); return them and whether a smaller document has the very same segment."""
    rows = rows[np.lexsort((rows["doc"], rows["segment"], rows["gram"]))]
    fresh = np.concatenate([[True], (rows["gram"][1:] != rows["gram"][:-1]) | (rows["segment"][1:] != rows["segment"][:-1])])
    heads = np.flatnonzero(fresh)
    least = np.repeat(rows["doc"][heads], np.diff(np.concatenate([heads, [len(rows)]])))
    return rows, rows["doc"] > least


def doc_bucket(doc, buckets: int):
    return (doc ^ (doc.view(np.uint64) >> np.uint64(15)).view(np.int64)) % buckets


def doc_bucket_column(doc, buckets: int):
    return F.pmod(doc.bitwiseXOR(F.shiftrightunsigned(doc, 15)), F.lit(buckets)).cast("int")


def _parcels(rows: np.ndarray, key: np.ndarray):
    """(key, rows of that key, by document) in key order: columns of neighbours alike compress well."""
    order = np.lexsort((rows["ord"], rows["doc"], key))
    rows, key = rows[order], key[order]
    cuts = np.flatnonzero(np.diff(key)) + 1
    for part, k in zip(np.split(rows, cuts), key[np.concatenate([[0], cuts])] if len(key) else []):
        yield int(k), part


def _marks(rows: np.ndarray, state: np.ndarray) -> np.ndarray:
    out = np.empty(len(rows), dtype=MARK)
    for name in ("doc", "print", "ord", "gram"):
        out[name] = rows[name]
    out["state"] = state
    out["gram"][out["state"] == COVERED] = 0
    return out


def _columns(rows: np.ndarray) -> bytes:
    """Field after field: alike bytes lie together, which compresses."""
    return b"".join(np.ascontiguousarray(rows[name]).tobytes() for name in rows.dtype.names)


def _rows(blob: bytes, kind: np.dtype) -> np.ndarray:
    n, at = len(blob) // kind.itemsize, 0
    out = np.empty(n, dtype=kind)
    for name in kind.names:
        out[name] = np.frombuffer(blob, dtype=kind[name], count=n, offset=at)
        at += n * kind[name].itemsize
    return out


def _ship(buckets: int):
    """Texts -> segments by gram bucket (kind 0), and what the task settled itself by document bucket (kind 1)."""

    def flush(held):
        rows, covered = settle(np.concatenate(held))
        out = [(0, k, _columns(part)) for k, part in _parcels(rows[~covered], (rows["gram"][~covered] % np.uint64(buckets)).astype(np.int64))]
        gone = rows[covered]
        out += [(1, k, _columns(_marks(part, np.uint8(COVERED)))) for k, part in _parcels(gone, doc_bucket(np.ascontiguousarray(gone["doc"]), buckets))]
        for i in range(0, len(out), 64):
            some = out[i : i + 64]
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in some], pa.int32()), pa.array([x[1] for x in some], pa.int32()), pa.array([x[2] for x in some], pa.binary())], ["kind", "bucket", "data"])

    def run(batches):
        held, size = [], 0
        for batch in (b.slice(i, 1000) for b in batches for i in range(0, b.num_rows, 1000)):
            docs = batch.column(0).to_numpy(zero_copy_only=False)
            texts = batch.column(1).to_pylist()
            for i, z in chunks(texts):
                text, ordinal, _, _, gram, body, _ = segments(texts[i:z])
                if not len(text):
                    continue
                rows = np.empty(len(text), dtype=BLOB)
                prints = np.array([fingerprint(t) for t in texts[i:z]], dtype=np.uint32)
                rows["doc"], rows["print"], rows["ord"], rows["gram"], rows["segment"] = docs[i:z][text], prints[text], ordinal, gram, body
                held.append(rows)
                size += len(rows)
                if size >= HELD:
                    yield from flush(held)
                    held, size = [], 0
        if held:
            yield from flush(held)

    return run


def _meet(buckets: int, crowd: int):
    """Segments of a gram bucket meet: covered ones and those that must be compared go to their documents' buckets."""

    def solve(bucket, blobs):
        rows, covered = settle(np.concatenate([_rows(b, BLOB) for b in blobs]))
        heads = np.flatnonzero(np.concatenate([[True], rows["gram"][1:] != rows["gram"][:-1]]))
        sizes = np.diff(np.concatenate([heads, [len(rows)]]))
        open_docs = np.where(covered, rows["doc"][np.repeat(heads, sizes)], rows["doc"])
        differ = np.repeat(np.minimum.reduceat(open_docs, heads) < np.maximum.reduceat(open_docs, heads), sizes)
        classes = np.repeat(np.add.reduceat((~covered).astype(np.int64), heads), sizes)
        state = np.where(covered, COVERED, np.where(classes > crowd, CROWDED, PARTIAL)).astype(np.uint8)
        tell = covered | differ
        marks = _marks(rows[tell], state[tell])
        return [(1, k, _columns(part)) for k, part in _parcels(marks, doc_bucket(np.ascontiguousarray(marks["doc"]), buckets))]

    def run(batches):
        current, blobs = None, []
        for batch in batches:
            out = []
            for kind, bucket, data in zip(*(batch.column(i).to_pylist() for i in range(3))):
                if kind == 1:
                    out.append((kind, bucket, data))
                    continue
                if bucket != current and blobs:
                    out += solve(current, blobs)
                    blobs = []
                current = bucket
                blobs.append(data)
            yield from pack(out)
        if blobs:
            yield from pack(solve(current, blobs))

    def pack(out):
        for i in range(0, len(out), 256):
            some = out[i : i + 256]
            yield pa.RecordBatch.from_arrays([pa.array([x[1] for x in some], pa.int32()), pa.array([x[2] for x in some], pa.binary())], ["bucket", "data"])

    return run


class _Found:
    """Rows of the second pass, by kind: finished documents, windows to compare, texts that wait for them."""

    NAMES = ["kind", "key", "doc_id", "print", "ord", "data", "covered", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
    TYPES = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.string()]
    SCHEMA = "kind int, key bigint, doc_id bigint, print bigint, ord bigint, data binary, covered binary, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string"
    DONE, WINDOWS, WAITING = 0, 1, 2

    def __init__(self):
        self.rows: list[tuple] = []

    def batches(self):
        for i in range(0, len(self.rows), 2000):
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*self.rows[i : i + 2000]), self.TYPES)], self.NAMES)
        self.rows = []


def carve(text: bytes, spans: list[tuple[np.ndarray, np.ndarray]]) -> tuple[int, int, str]:
    """(bytes removed, maximal runs, SHA-256 of the rest) for lists of [first, end) runs."""
    edge = np.zeros(len(text) + 1, dtype=np.int64)
    for first, end in spans:
        np.add.at(edge, first, 1)
        np.add.at(edge, end, -1)
    gone = np.cumsum(edge)[:-1] > 0
    runs = int(np.count_nonzero(np.diff(np.concatenate([[0], gone.astype(np.int8)])) == 1))
    return int(gone.sum()), runs, hashlib.sha256(np.frombuffer(text, dtype=np.uint8)[~gone].tobytes()).hexdigest()


def _by_document(marks: np.ndarray) -> dict[tuple[int, int], np.ndarray]:
    marks = marks[np.lexsort((marks["print"], marks["doc"]))]
    if not len(marks):
        return {}
    cuts = np.flatnonzero((np.diff(marks["doc"]) != 0) | (np.diff(marks["print"]) != 0)) + 1
    return {(int(p["doc"][0]), int(p["print"][0])): p for p in np.split(marks, cuts)}


def _apply(batches):
    """Marks of a document bucket (kind 0) precede its texts (kind 1)."""
    bucket, blobs, marks, out = None, [], {}, _Found()
    for batch in (b.slice(i, 500) for b in batches for i in range(0, b.num_rows, 500)):
        keys, kinds, docs, data = (batch.column(i).to_pylist() for i in range(4))
        texts: list[tuple[int, bytes]] = []
        for b, kind, doc, blob in zip(keys, kinds, docs, data):
            if b != bucket:
                _resolve(texts, marks, bucket, out)
                bucket, blobs, marks, texts = b, [], {}, []
            if kind == 0:
                blobs.append(blob)
            else:
                if blobs:
                    marks, blobs = _by_document(np.concatenate([_rows(x, MARK) for x in blobs])), []
                texts.append((doc, blob))
        _resolve(texts, marks, bucket, out)
        yield from out.batches()


def _resolve(texts, marks, bucket, out: _Found) -> None:
    touched = []
    for doc, text in texts:
        own = marks.get((doc, fingerprint(text))) if doc is not None else None
        if own is None:
            out.rows.append((out.DONE, 0, doc, 0, 0, None, None, len(text), 0, 0, hashlib.sha256(text).hexdigest()))
        else:
            touched.append((doc, text, own))
    for i, z in chunks([t[1] for t in touched]):
        some = touched[i:z]
        index, _, first, last, _, _, data = segments([t[1] for t in some])
        base = np.concatenate([[0], np.cumsum([len(t[1]) for t in some])])
        opening = np.searchsorted(index, np.arange(len(some) + 1))
        for k, (doc, text, own) in enumerate(some):
            a, e = first[opening[k] : opening[k + 1]] - base[k], last[opening[k] : opening[k + 1]] - base[k] + SPAN
            gone = own["ord"][own["state"] == COVERED]
            todo = own[own["state"] != COVERED]
            if not len(todo):
                out.rows.append((out.DONE, 0, doc, 0, 0, None, None, len(text), *carve(text, [(a[gone], e[gone])])))
                continue
            mark = fingerprint(text)
            out.rows.append((out.WAITING, bucket, doc, mark, 0, text, gone.astype("<u4").tobytes(), len(text), 0, 0, None))
            for row in todo:
                o, gram = int(row["ord"]), int(row["gram"].astype(np.int64))
                if row["state"] == PARTIAL:
                    out.rows.append((out.WINDOWS, gram, doc, mark, o << 8, text[a[o] : e[o]], None, 0, 0, 0, None))
                else:
                    for w in range(int(a[o]), int(e[o]) - SPAN + 1):
                        own_key = int.from_bytes(hashlib.blake2b(text[w : w + SPAN], digest_size=8, key=gram.to_bytes(8, "little", signed=True)).digest(), "little", signed=True)
                        out.rows.append((out.WINDOWS, own_key, doc, mark, o << 8 | (w - int(a[o])), text[w : w + SPAN], None, 0, 0, 0, None))


def _words(data: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """The first SPAN bytes of each suffix as big-endian numbers of eight bytes, the last one filled up with zeros."""
    text = np.lib.stride_tricks.sliding_window_view(data, SPAN)[starts]
    full = np.zeros((len(starts), -(-SPAN // 8) * 8), dtype=np.uint8)
    full[:, :SPAN] = text
    return full.view(">u8").astype(np.uint64)


def _split(order: np.ndarray, part: np.ndarray, *keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sort each part (a run of order) by keys, the first one counts most: new order, new parts, and the sort's permutation."""
    by = np.lexsort((*keys[::-1], part))
    fresh = np.zeros(len(by), dtype=bool)
    for x in (part, *keys):
        x = x[by]
        fresh[1:] |= x[1:] != x[:-1]
    return order[by], np.cumsum(fresh), by


def _runs(part: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First place and length of each run of equal numbers."""
    first = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]]))
    return first, np.diff(np.concatenate([first, [len(part)]]))


def _refine(order: np.ndarray, part: np.ndarray, open_: np.ndarray, step) -> None:
    """Rounds of step(suffixes, their parts) -> (sort keys, whether a part that comes out stays open), on the open parts only.

    order and part are changed in place; numbers of parts rise with the order and have gaps for the parts to come."""
    while open_.any():
        places = np.flatnonzero(open_)
        some, own = order[places], part[places]
        keys, more = step(some, own)
        sorted_, _, by = _split(some, own, *keys)
        order[places] = sorted_
        fresh = np.concatenate([[True], np.any([(x[by][1:] != x[by][:-1]) for x in (own, *keys)], axis=0)])
        heads = np.flatnonzero(fresh)
        part[places] = places[np.repeat(heads, np.diff(np.concatenate([heads, [len(places)]])))]
        _, sizes = _runs(part[places])
        open_[places] = more[by] & (np.repeat(sizes, sizes) > 1)


def suffix_order(data: np.ndarray, starts: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes in the order of (group, first SPAN bytes), and for each place of it whether a new string begins there.

    Shallow: multikey quicksort with eight bytes as one character. Each round takes a pivot, the median of three, in every
    open part and splits it into the less, the equal, which go on with the next character, and the greater, until a part
    agrees in its first SHALLOW bytes. Deep: blind tries. Each round takes one suffix of every open part as the path of its
    trie; the others look for the character where they leave the path, from the word on that the part is known to agree to,
    and hang below that branching position by their byte there. Branches to lesser bytes come before the path, the
    nearest to the root first, those to greater bytes after it, the nearest to the root last; what agrees to SPAN stays on the
    path. Each branch is an open part, and a trie, of the next round."""
    words = _words(data, starts)
    order = np.argsort(group, kind="stable")
    first, sizes = _runs(group[order])
    part = np.repeat(first, sizes)
    depth = np.zeros(len(starts), dtype=np.int64)  # words that a suffix's part agrees in

    def quick(some, own):
        first, sizes = _runs(own)
        key = words[some, depth[some]]
        three = np.sort(np.stack([key[first], key[first + sizes // 2], key[first + sizes - 1]]), axis=0)
        pivot = np.repeat(three[1], sizes)
        side = np.where(key < pivot, 0, np.where(key == pivot, 1, 2))
        depth[some[side == 1]] += 1
        return (side,), depth[some] * 8 < SHALLOW

    _refine(order, part, np.repeat(sizes, sizes) > 1, quick)

    def trie(some, own):
        first, sizes = _runs(own)
        path = np.repeat(some[first], sizes)
        last = words.shape[1]
        at = depth[some].copy()
        look = np.flatnonzero(at < last)
        while len(look):  # word by word, those that still agree with the path
            look = look[words[some[look], at[look]] == words[path[look], at[look]]]
            at[look] += 1
            look = look[at[look] < last]
        same = at == last
        word = np.minimum(at, last - 1)
        mine, theirs = words[some, word], words[path, word]
        differ = mine ^ theirs
        byte = np.zeros(len(some), dtype=np.int64)
        for shift in (8, 16, 24, 32, 40, 48, 56):
            byte += differ < (np.uint64(1) << np.uint64(64 - shift))
        branch = np.where(same, 0, at * 8 + byte)
        letter = np.where(same, 0, (mine >> (np.uint64(56) - byte.astype(np.uint64) * np.uint64(8))) & np.uint64(255)).astype(np.int64)
        side = np.where(same, 1, np.where(mine < theirs, 0, 2))
        depth[some] = np.where(same, last, at)
        return (side, np.where(side == 2, -branch, branch), letter), ~same

    _, sizes = _runs(part)
    _refine(order, part, np.repeat(sizes, sizes) > 1, trie)
    return order, np.concatenate([[True], part[1:] != part[:-1]]) if len(part) else np.empty(0, dtype=bool)


def _compare(buckets: int):
    """Segments of one key, together and in key order -> windows that a smaller document holds, as a mask per segment."""

    def solve(keys, docs, prints, ords, data):
        lengths = np.array([len(d) for d in data], dtype=np.int64)
        windows = lengths - SPAN + 1
        firsts = np.cumsum(lengths) - lengths
        offset = np.arange(windows.sum()) - np.repeat(np.cumsum(windows) - windows, windows)
        owner = np.repeat(np.arange(len(data)), windows)
        order, fresh = suffix_order(np.frombuffer(b"".join(data), dtype=np.uint8), firsts[owner] + offset, np.array(keys, dtype=np.int64)[owner])
        doc = np.array(docs, dtype=np.int64)[owner]
        heads = np.flatnonzero(fresh)
        least = np.repeat(np.minimum.reduceat(doc[order], heads), np.diff(np.concatenate([heads, [len(order)]])))
        hit = np.empty(len(order), dtype=bool)
        hit[order] = doc[order] > least
        ords = np.array(ords, dtype=np.int64)
        bits = np.where(hit, np.int64(1) << (offset + (ords & 255)[owner]), 0)
        masks = np.add.reduceat(bits, np.cumsum(windows) - windows)
        told = masks != 0
        docs = np.array(docs, dtype=np.int64)[told]
        return pa.RecordBatch.from_arrays(
            [pa.array(doc_bucket(docs, buckets)), pa.array(docs), pa.array(np.array(prints, dtype=np.int64)[told]), pa.array(ords[told] >> 8), pa.array(masks[told])],
            ["key", "doc_id", "print", "ord", "mask"],
        )

    def run(batches):
        rows: list[list] = [[], [], [], [], []]
        for batch in batches:
            columns = [batch.column(i).to_pylist() for i in range(5)]
            for held, new in zip(rows, columns):
                held += new
            if len(rows[0]) >= 20_000 and rows[0][0] != rows[0][-1]:
                keep = len(rows[0]) - 1
                while rows[0][keep - 1] == rows[0][-1]:
                    keep -= 1
                yield solve(*(r[:keep] for r in rows))
                rows = [r[keep:] for r in rows]
        if rows[0]:
            yield solve(*rows)

    return run


def _finish(batches):
    """Masks of a document bucket (kind 0) precede its waiting texts (kind 1)."""
    bucket, masks = None, {}
    for batch in (b.slice(i, 500) for b in batches for i in range(0, b.num_rows, 500)):
        out = _Found()
        for b, kind, doc, mark, ordinal, mask, text, covered in zip(*(batch.column(i).to_pylist() for i in range(8))):
            if b != bucket:
                bucket, masks = b, {}
            if kind == 0:
                masks.setdefault((doc, mark), []).append((ordinal, mask))
                continue
            _, _, a, z, _, _, _ = segments([text])
            gone = np.frombuffer(covered, dtype="<u4").astype(np.int64)
            spans = [(a[gone], z[gone] + SPAN)]
            for ordinal, mask in masks.get((doc, mark), ()):
                on = a[ordinal] + np.flatnonzero(np.array([mask >> j & 1 for j in range(WIDE)]))
                spans.append((on, on + SPAN))
            out.rows.append((out.DONE, 0, doc, 0, 0, None, None, len(text), *carve(text, spans)))
        yield from out.batches()


def dedup_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", crowd: int = CROWD) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 per row."""
    require_columns(docs, id_col, text_col)
    with small_batches(docs.sparkSession):
        return _dedup(docs, id_col, text_col, crowd)


def _dedup(docs: DataFrame, id_col: str, text_col: str, crowd: int) -> DataFrame:
    spark = docs.sparkSession
    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary").alias("data"))
    volume = narrow.agg(F.coalesce(F.sum(F.octet_length("data")), F.lit(0)).alias("b")).first()["b"]  # one row
    buckets = max(shuffle_width(spark), -(-int(volume) // TASK_BYTES))
    shipped = narrow.filter("doc_id is not null and octet_length(data) >= %d" % SPAN).mapInArrow(trimmed(_ship(buckets)), "kind int, bucket int, data binary")
    met = shipped.repartition(buckets, "kind", "bucket").sortWithinPartitions("kind", "bucket").mapInArrow(trimmed(_meet(buckets, crowd)), "bucket int, data binary")
    marks = cut(met, "segment-marks")
    del shipped, met
    release(spark)
    texts = narrow.select(F.coalesce(doc_bucket_column(F.col("doc_id"), buckets), F.lit(0)).alias("bucket"), F.lit(1).alias("kind"), "doc_id", "data")
    both = marks.select("bucket", F.lit(0).alias("kind"), F.lit(None).cast("long").alias("doc_id"), "data").union(texts)
    seen = both.repartition(buckets, "bucket").sortWithinPartitions("bucket", "kind").mapInArrow(trimmed(_apply), _Found.SCHEMA)
    seen = cut(seen, "judged-texts")
    discard(marks)
    del both
    release(spark)
    windows = seen.filter(F.col("kind") == _Found.WINDOWS).select("key", "doc_id", "print", "ord", "data")
    masks = windows.repartition(buckets, "key").sortWithinPartitions("key").mapInArrow(trimmed(_compare(buckets)), "key bigint, doc_id bigint, print bigint, ord bigint, mask bigint")
    answers = masks.select("key", F.lit(0).alias("kind"), "doc_id", "print", "ord", "mask", F.lit(None).cast("binary").alias("data"), F.lit(None).cast("binary").alias("covered"))
    waiting = seen.filter(F.col("kind") == _Found.WAITING).select("key", F.lit(1).alias("kind"), "doc_id", "print", F.lit(0).cast("long").alias("ord"), F.lit(0).cast("long").alias("mask"), "data", "covered")
    late = answers.union(waiting).repartition(buckets, "key").sortWithinPartitions("key", "kind").mapInArrow(trimmed(_finish), _Found.SCHEMA)
    final = ("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
    late = cut(late.select(*final), "late-texts")
    return seen.filter(F.col("kind") == _Found.DONE).select(*final).union(late)


ORACLE = """
WITH h AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
w AS (SELECT doc_id, i, substr(x, 2 * i + 1, 100) AS s FROM (SELECT doc_id, x, unnest(range(0, greatest(len(x) // 2 - 49, 0))) AS i FROM h)),
f AS (SELECT s, min(doc_id) AS m FROM w GROUP BY s),
c AS (SELECT w.doc_id, w.i, lag(w.i) OVER o AS before, lead(w.i) OVER o AS after FROM w JOIN f ON f.s = w.s AND f.m < w.doc_id WINDOW o AS (PARTITION BY w.doc_id ORDER BY w.i)),
d AS (SELECT *, sum(CASE WHEN before IS NULL OR i - before > 50 THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY i) AS span FROM c),
r AS (SELECT doc_id, span, min(i) AS a, max(i) + 50 AS z FROM d GROUP BY doc_id, span),
q AS (SELECT r.doc_id, r.a, r.z, h.x, coalesce(lag(r.z) OVER (PARTITION BY r.doc_id ORDER BY r.a), 0) AS prior FROM r JOIN h USING (doc_id)),
t AS (SELECT doc_id, count(*) AS n_spans, sum(z - a) AS n_removed, string_agg(substr(x, 2 * prior + 1, 2 * (a - prior)), '' ORDER BY a) || substr(any_value(x), 2 * max(z) + 1) AS kept FROM q GROUP BY doc_id)
SELECT h.doc_id, CAST(len(h.x) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(t.n_removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(t.n_spans, 0) AS BIGINT) AS n_spans, sha256(unhex(coalesce(t.kept, h.x))) AS kept_sha256
FROM h LEFT JOIN t USING (doc_id)
"""
