"""Removal of repeated 100-byte strings by bucket-pointer refinement.

Tasks agree on 64-bit names that are made from content: 8-byte strings, paired to 16, 32, 64 and 100 bytes. Of
each 100-byte string the place of its smallest 32-byte name (its anchor) is chosen, so equal strings have equal
anchors at equal offsets.

1. Places whose strings share an anchor form a run. Runs meet by anchor name; only the first run of each
   content stays, and in a bucket with one content no more is to be decided.
2. The strings of buckets with several contents are put in order within a part: buckets of the 8-byte strings
   that suffixes begin with are refined by sorting each bucket on the bucket pointers of a later offset; a
   pointer that was refined is used by all refinements that follow, and buckets of one suffix are left alone.
   So the bytes themselves decide which strings of a part are equal; the first of each goes on and meets those
   of other parts by two names (96 bits).
3. What is not a first occurrence is repeated; the bytes that it covers are removed.

Rows between tasks are packed arrays dealt by identifier, each task sends only its own first occurrence of
anything, and a part holds about PART_BYTES of text, so neither hot passages nor hot copies gather anywhere.

Defined cases: a null or empty text has 0 bytes; rows that repeat an id are versions of one document, none
earlier than the other: equal rows get equal answers; rows with a null id come before all others and their
answers carry a null id; an empty table gives an empty result; a very long text is cut into blocks that overlap by
a string, and is put back whole; extra columns are carried by cleaned_documents() and left out by remove_repeats().
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NO_ID, freeing, parts_for, release, spans, utf8
from .common import ids as ids_of

LENGTH = 100
ANCHOR = 32
WIDTH = LENGTH - ANCHOR + 1
BLOCK_BYTES = 1 << 19
PART_BYTES = 24 << 20
#: Bytes of undecided runs, and rows of strings, that a task puts in order at once.
SLICE_BYTES, SLICE_ROWS = 2 << 20, 1 << 20
BLOB = "part int, kind int, blob binary"
# Packed columns: of runs (bucket, content, document, place, places more), of decided runs (document, place,
# more, several contents), of strings (two identifiers, document, place), of first strings, of texts.
RUNS, DECIDED, STRINGS, FIRSTS, TEXTS = "u8 u8 di8 du4 u1", "di8 du4 u1 u1", "u8 u4 di8 du4", "di8 du4", "di8 i8"
_C = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB)]


def _mix(x: np.ndarray) -> np.ndarray:
    x ^= x >> np.uint64(32)
    x *= _C[3]
    x ^= x >> np.uint64(29)
    return x


def _refine(names: np.ndarray, step: int, by: np.uint64) -> np.ndarray:
    """Identifiers of longer strings: each place's with the one `step` later."""
    out = names[:-step] * by
    out += names[step:]
    return _mix(out)


def names(data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Identifiers of all 32-byte strings, of all 100-byte strings, and a second one of the latter."""
    n = len(data) - 7
    h = _mix(np.ndarray((n,), np.uint64, data.tobytes(), strides=(1,)) * _C[0])
    short = _refine(_refine(h, 8, _C[0]), 16, _C[1])
    h = _refine(short, 32, _C[2])
    full = _refine(h, LENGTH - 64, _C[4])
    return short, full, h


def refine_buckets(data: np.ndarray, length: int = LENGTH) -> np.ndarray:
    """A pointer for each place: equal for two places exactly if the strings of `length` bytes there are equal.

    Places less than `length` from the end get a pointer without meaning.
    """
    n = len(data)
    words = np.ndarray((n - 7,), ">u8", data.tobytes(), strides=(1,)).astype(np.uint64)
    words = np.concatenate([words, np.zeros(7, np.uint64)])
    order = np.argsort(words)
    held = words[order]
    first = np.ones(n, bool)
    first[1:] = held[1:] != held[:-1]
    del words, held
    lead = np.flatnonzero(first)
    pointer = np.empty(n, np.int64)
    pointer[order] = np.repeat(lead, np.diff(lead, append=n))
    live = order[~(first & np.append(first[1:], True))]  # in order of their buckets; buckets of one are done
    depth = 8
    while depth < length and len(live):
        step = min(depth, length - depth)
        key = pointer[live] << 32 | pointer[np.minimum(live + step, n - 1)]
        turn = np.argsort(key)
        live, key = live[turn], key[turn]
        old = key >> 32
        first, bucket = np.ones(len(live), bool), np.ones(len(live), bool)
        first[1:], bucket[1:] = key[1:] != key[:-1], old[1:] != old[:-1]
        at = np.arange(len(live))
        start = np.maximum.accumulate(np.where(first, at, 0))
        pointer[live] = old + start - np.maximum.accumulate(np.where(bucket, at, 0))
        live = live[~(first & np.append(first[1:], True))]
        depth += step
    return pointer


def _runs(data: np.ndarray, ok: np.ndarray) -> tuple[np.ndarray, ...]:
    """Maximal runs of valid places with one anchor: bucket, content, first place, places after the first."""
    short, full, _ = names(data)
    n = len(full)
    key = (short & ~np.uint64(0xFFFFF)) | np.arange(len(short), dtype=np.uint64)
    span, m = 1, key
    while span * 2 <= WIDTH:
        m = np.minimum(m[:-span], m[span:])
        span *= 2
    m = np.minimum(m[: n], m[WIDTH - span :][:n])
    anchor = (m & np.uint64(0xFFFFF)).astype(np.int64)
    new = np.ones(n, bool)
    new[1:] = anchor[1:] != anchor[:-1]
    new[1:] |= ok[1:n] != ok[: n - 1]
    lo = np.flatnonzero(new)
    hi = np.append(lo[1:], n) - 1
    good = ok[lo]
    lo, hi = lo[good], hi[good]
    a = anchor[lo]
    content = full[lo] * _C[1] + full[hi] * _C[2] + (a - lo).astype(np.uint64) * _C[4] + (hi - lo).astype(np.uint64) * _C[5]
    return short[a], _mix(content), lo, hi - lo


def _text_runs(data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
    """Blocks of (bucket, content, text, place, more) over all texts. Long texts are cut with enough overlap
    that each run is seen whole by the block it starts in."""
    for i, j in spans(offsets, BLOCK_BYTES):
        base, end = offsets[i], offsets[j]
        if end - base <= 2 * BLOCK_BYTES:
            if end - base < LENGTH:
                continue
            part = data[base:end]
            ok = np.ones(len(part), bool)
            for back in (offsets[i + 1 : j + 1] - base,):
                edge = np.zeros(len(part) + 1, np.int32)
                starts = np.maximum(back - LENGTH + 1, offsets[i:j] - base)
                np.add.at(edge, starts, 1)
                np.add.at(edge, back, -1)
                ok = np.cumsum(edge)[:-1] == 0
            bucket, content, lo, more = _runs(part, ok)
            yield bucket, content, np.searchsorted(offsets, lo + base, "right") - 1, lo + base, more
        else:
            for s in range(base, end - LENGTH + 1, BLOCK_BYTES):
                first = max(base, s - 1)
                part = data[first : min(end, s + BLOCK_BYTES + WIDTH + LENGTH)]
                if len(part) < LENGTH:
                    continue
                bucket, content, lo, more = _runs(part, np.ones(len(part), bool))
                own = (lo + first >= s) & (lo + first < s + BLOCK_BYTES)
                # A run that began before this block is cut at its edge; the block before has it whole.
                lo = lo + first
                if first < s:
                    own &= ~((lo == s) & (np.cumsum(np.ones(len(lo), np.int64)) == 1))
                yield bucket[own], content[own], np.full(own.sum(), i), lo[own], more[own]


def _pack(kinds: str, *columns: np.ndarray) -> bytes:
    """Columns of one length, those marked d as steps from row to row, squeezed together."""
    import zstandard

    raw = []
    for kind, c in zip(kinds.split(), columns):
        c = c.astype(kind[1:] if kind[0] == "d" else kind)
        raw.append((np.diff(c, prepend=c.dtype.type(0)) if kind[0] == "d" else c).tobytes())
    return len(columns[0]).to_bytes(8, "little") + zstandard.ZstdCompressor(level=1).compress(b"".join(raw))


def _unpack(blob: bytes, kinds: str) -> list[np.ndarray]:
    import zstandard

    n, at, out = int.from_bytes(blob[:8], "little"), 0, []
    raw = zstandard.ZstdDecompressor().decompress(blob[8:]) if n else b""
    for kind in kinds.split():
        dtype = np.dtype(kind[1:] if kind[0] == "d" else kind)
        c = np.frombuffer(raw, dtype, n, at) if n else np.zeros(0, dtype)
        out.append(np.cumsum(c, dtype=dtype) if kind[0] == "d" else c)
        at += dtype.itemsize * n
    return out


def _gather(blobs: list, kinds: str) -> list[np.ndarray]:
    parts = [_unpack(b, kinds) for b in blobs]
    return [np.concatenate([p[k] for p in parts]) if parts else np.zeros(0, kind[-2:]) for k, kind in enumerate(kinds.split())]


def _part(x: np.ndarray, parts: int) -> np.ndarray:
    return ((x >> np.uint64(33)) % np.uint64(parts)).astype(np.int32)


def _doc_part(doc: np.ndarray, parts: int) -> np.ndarray:
    return _part(_mix(doc.astype(np.int64).view(np.uint64) * _C[0] + _C[5]), parts)


def _deal(kinds: str, part: np.ndarray, kind: int, *columns: np.ndarray) -> Iterator[pa.RecordBatch]:
    """A packed row for each part."""
    order = np.argsort(part, kind="stable")
    part = part[order]
    cuts = [0, *(np.flatnonzero(part[1:] != part[:-1]) + 1), len(part)]
    columns = [c[order] for c in columns]
    ids = [int(part[a]) for a in cuts[:-1]] if len(part) else []
    for k in range(0, len(ids), 64):
        some = range(k, min(k + 64, len(ids)))
        blobs = [_pack(kinds, *[c[cuts[x] : cuts[x + 1]] for c in columns]) for x in some]
        yield pa.RecordBatch.from_arrays([pa.array([ids[x] for x in some], pa.int32()), pa.array([kind] * len(blobs), pa.int32()), pa.array(blobs, pa.binary())], ["part", "kind", "blob"])


def _firsts(keys: list[np.ndarray], doc: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Rows with the smallest (doc, place) of their key; all of them where rows repeat."""
    order = np.lexsort((place, doc, *reversed(keys)))
    new = np.zeros(len(order), bool)
    if len(order):
        new[0] = True
        for k in keys:
            new[1:] |= k[order[1:]] != k[order[:-1]]
    return order, new


def _anchor_rows(parts: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, (data, offsets) = ids_of(batch.column(0)), utf8(batch.column(1))
            blocks = list(_text_runs(data, offsets))
            if not blocks:
                continue
            bucket, content, text, place, more = (np.concatenate([b[k] for b in blocks]) for k in range(5))
            doc, place = ids[text], place - offsets[text]
            order, new = _firsts([bucket, content], doc, place)
            keep = order[new]
            keep = keep[np.lexsort((place[keep], doc[keep]))]
            yield from _deal(RUNS, _part(bucket[keep], parts), 0, bucket[keep], content[keep], doc[keep], place[keep], more[keep])

    return kernel


def _decide_runs(parts: int):
    """First runs of each content, with 1 where their bucket has several contents."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blobs = [x.as_py() for batch in batches for x in batch.column(2)]
        bucket, content, doc, place, more = _gather(blobs, RUNS)
        blobs.clear()
        order, new = _firsts([bucket, content], doc, place)
        keep = order[new]
        b = bucket[keep]
        same = b[1:] == b[:-1]
        several = np.append(same, False) | np.append(False, same)
        by_doc = np.lexsort((place[keep], doc[keep]))
        keep, several = keep[by_doc], several[by_doc]
        yield from _deal(DECIDED, _doc_part(doc[keep], parts), 0, doc[keep], place[keep], more[keep], several)

    return kernel


def _text_rows(parts: int):
    """Compressed blocks of texts by document part, with the columns after the text."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        squeeze = zstandard.ZstdCompressor(level=3)
        for batch in batches:
            ids, (data, offsets) = ids_of(batch.column(0)), utf8(batch.column(1))
            part = _doc_part(ids, parts)
            order = np.argsort(part, kind="stable")
            cuts = np.searchsorted(part[order], np.arange(parts + 1))
            for p in np.unique(part):
                rows = order[cuts[p] : cuts[p + 1]]
                sizes = offsets[rows + 1] - offsets[rows]
                at = np.concatenate([[0], np.cumsum(sizes)])
                for a, b in spans(at, 8 * BLOCK_BYTES):
                    text = b"".join(data[offsets[r] : offsets[r + 1]].tobytes() for r in rows[a:b])
                    head, other = _pack(TEXTS, ids[rows[a:b]], sizes[a:b]), b""
                    if batch.num_columns > 2:
                        sink = pa.BufferOutputStream()
                        held = pa.record_batch([c.take(pa.array(rows[a:b])) for c in batch.columns[2:]], names=batch.schema.names[2:])
                        with pa.ipc.new_stream(sink, held.schema) as stream:
                            stream.write_batch(held)
                        other = squeeze.compress(sink.getvalue().to_pybytes())
                    blob = b"".join([len(head).to_bytes(8, "little"), head, len(other).to_bytes(8, "little"), other, squeeze.compress(text)])
                    yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), pa.array([1], pa.int32()), pa.array([blob], pa.binary())], ["part", "kind", "blob"])

    return kernel


def _texts(blobs: list) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, bytes]]:
    """(ids, offsets, bytes, other columns) of each block of _text_rows."""
    import zstandard

    for blob in blobs:
        cut = 8 + int.from_bytes(blob[:8], "little")
        last = cut + 8 + int.from_bytes(blob[cut : cut + 8], "little")
        ids, sizes = _unpack(blob[8:cut], TEXTS)
        data = zstandard.ZstdDecompressor().decompress(blob[last:]) if sizes.sum() else b""
        yield ids, np.concatenate([[0], np.cumsum(sizes)]), np.frombuffer(data, np.uint8), blob[cut + 8 : last]


def _kinds(table: pa.Table, kind: int) -> list[bytes]:
    return [b.as_py() for k, b in zip(table.column("kind"), table.column("blob")) if k.as_py() == kind]


def _spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """start, start + 1, ... for each start and size."""
    total = np.cumsum(sizes)
    return np.repeat(starts - (total - sizes), sizes) + np.arange(total[-1] if len(total) else 0)


def _of_ids(doc: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each id the slice of the sorted doc array: starts and sizes."""
    a, b = np.searchsorted(doc, ids, "left"), np.searchsorted(doc, ids, "right")
    return a, b - a


def _anchor_of(held: np.ndarray, cut: np.ndarray) -> np.ndarray:
    """The least 32-byte name in the first string of each run: equal strings have equal ones, wherever they stand."""
    short = np.append(names(held)[0] & ~np.uint64(0xFFFFF), np.uint64(0))
    return np.minimum.reduceat(short, np.stack([cut[:-1], cut[:-1] + WIDTH], 1).ravel())[::2]


def _slices(names_: np.ndarray, total: int, most: int) -> tuple[np.ndarray, int]:
    """Number of the slice of each row, by its name, and how many slices of about `most` out of `total` there are."""
    count = max(1, -(-total // most))
    return (_mix(names_ * _C[3]) >> np.uint64(20)) % np.uint64(count), count


def _open_strings(parts: int):
    """Names of the strings of undecided runs, the part's first of each, by their bytes.

    Runs are dealt to slices by their anchors, so equal strings meet in one slice, and a slice is ordered at a time:
    the share of undecided runs grows with the table, what is held at once does not.
    """

    def kernel(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(batches)
        doc, place, more, several = _gather(_kinds(table, 0), DECIDED)
        held = several == 1
        doc, place, more = doc[held], place[held].astype(np.int64), more[held].astype(np.int64)
        order = np.argsort(doc, kind="stable")
        doc, place, more = doc[order], place[order], more[order]
        found, length = [], 0
        texts = _kinds(table, 1)
        del table
        for ids, offsets, data, _ in _texts(texts):
            a, n = _of_ids(doc, ids)
            rows = _spread(a, n)
            text = np.repeat(np.arange(len(ids)), n)
            lo, size = place[rows] + offsets[text], more[rows] + LENGTH
            fits = lo + size <= offsets[text + 1]  # a version of the document may be shorter
            text, lo, size, rows = text[fits], lo[fits], size[fits], rows[fits]
            if not len(rows):
                continue
            whole = np.concatenate([[0], np.cumsum(size)])
            for i, j in spans(whole, SLICE_BYTES):
                held, cut = data[_spread(lo[i:j], size[i:j])], whole[i : j + 1] - whole[i]
                found.append((held, cut, _anchor_of(held, cut), ids[text[i:j]], place[rows[i:j]]))
                length += len(held)
        del texts
        ready: list[tuple] = []
        for k in range(-(-length // SLICE_BYTES)):
            ready.append(_first_strings([_of_slice(f, length, k) for f in found]))
            if sum(len(r[0]) for r in ready) >= SLICE_ROWS:
                yield from _named(ready, parts)
                ready = []
        if ready:
            yield from _named(ready, parts)
        found.clear()
        release()

    return kernel


def _of_slice(block: tuple, length: int, k: int) -> tuple[np.ndarray, ...]:
    """Bytes, sizes, documents and places of the runs of a block that are in slice k."""
    held, cut, anchor, doc, place = block
    slice_, _ = _slices(anchor, length, SLICE_BYTES)
    at = np.flatnonzero(slice_ == k)
    size = cut[at + 1] - cut[at]
    return held[_spread(cut[at], size)], size, doc[at], place[at]


def _first_strings(blocks: list[tuple]) -> tuple[np.ndarray, ...]:
    """Two names, document and place of the first of each string, by the bytes of all blocks together."""
    held, size, doc, place = (np.concatenate([b[i] for b in blocks]) for i in range(4))
    if not len(size):
        return np.zeros(0, np.uint64), np.zeros(0, np.uint32), np.zeros(0, np.int64), np.zeros(0, np.uint32)
    count = size - LENGTH + 1
    own = _spread(np.concatenate([[0], np.cumsum(size)])[:-1], count)
    pointer = refine_buckets(held)[own]
    d, s = np.repeat(doc, count), _spread(place, count)
    order, new = _firsts([pointer], d, s)
    keep = order[new]
    del order, new, pointer
    _, full, half = names(held)
    at = own[keep]
    other = (half[at] * _C[1] ^ half[at + LENGTH - 64] * _C[5]) >> np.uint64(32)
    return full[at], other.astype(np.uint32), d[keep], s[keep].astype(np.uint32)


def _named(ready: list[tuple], parts: int) -> Iterator[pa.RecordBatch]:
    full, other, d, s = (np.concatenate([r[i] for r in ready]) for i in range(4))
    keep = np.lexsort((s, d))
    yield from _deal(STRINGS, _part(full[keep], parts), 0, full[keep], other[keep], d[keep], s[keep])


def _sliced(blobs: list[bytes], kinds: str, by: int) -> Iterator[list[np.ndarray]]:
    """The columns of all blobs in slices of about SLICE_ROWS, dealt by a column of names or documents."""
    total = sum(int.from_bytes(b[:8], "little") for b in blobs)
    for k in range(-(-total // SLICE_ROWS)):
        parts = []
        for b in blobs:
            columns = _unpack(b, kinds)
            at = np.flatnonzero(_slices(columns[by].view(np.uint64), total, SLICE_ROWS)[0] == k)
            parts.append([c[at] for c in columns])
        columns = [np.concatenate([p[i] for p in parts]) for i in range(len(parts[0]))]
        if len(columns[0]):
            yield columns


def _decide_strings(parts: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blobs = [x.as_py() for batch in batches for x in batch.column(2)]
        for full, other, doc, place in _sliced(blobs, STRINGS, 0):
            order, new = _firsts([full, other], doc, place)
            keep = order[new]
            keep = keep[np.lexsort((place[keep], doc[keep]))]
            yield from _deal(FIRSTS, _doc_part(doc[keep], parts), 2, doc[keep], place[keep])

    return kernel


def _first_runs(blobs: list[bytes]) -> list[np.ndarray]:
    """Document, place and size of the stretches of places where first strings start."""
    found = [[np.zeros(0, np.int64)] * 3]
    for doc, place in _sliced(blobs, FIRSTS, 0):
        order = np.lexsort((place, doc))
        doc, place = doc[order], place[order].astype(np.int64)
        new = np.ones(len(doc), bool)
        new[1:] = (doc[1:] != doc[:-1]) | (place[1:] > place[:-1] + 1)
        at = np.flatnonzero(new)
        last = np.append(at[1:], len(doc)) - 1
        found.append([doc[at], place[at], place[last] - place[at] + 1])
    return [np.concatenate([f[i] for f in found]) for i in range(3)]


def _remove(carried: list[str]):
    """Cuts the repeated bytes out of every text of a part: its figures, or its rest with the carried columns."""

    def kernel(left: pa.Table, right: pa.Table) -> pa.Table:
        import zstandard

        tables: list[pa.Table] = []
        doc, place, more, several = _gather(_kinds(left, 0), DECIDED)
        d2, s2, n2 = _first_runs(_kinds(right, 2))
        sure = several == 0
        doc = np.concatenate([doc[sure], d2])
        place = np.concatenate([place[sure], s2]).astype(np.int64)
        size = np.concatenate([more[sure].astype(np.int64) + 1, n2])
        order = np.argsort(doc, kind="stable")
        doc, place, size = doc[order], place[order], size[order]
        out: list[list] = [[], [], [], [], []]
        for ids, offsets, data, other in _texts(_kinds(left, 1)):
            a, n = _of_ids(doc, ids)
            rows, text = _spread(a, n), np.repeat(np.arange(len(ids)), n)
            total, last = int(offsets[-1]), offsets[text + 1]
            lo, hi = np.minimum(place[rows] + offsets[text], last), np.minimum(place[rows] + offsets[text] + size[rows], last)
            edge = np.zeros(total + 1, np.int32)
            np.add.at(edge, lo, 1)
            np.add.at(edge, hi, -1)
            first = np.cumsum(edge)[:-1] > 0
            tail = np.zeros(total + 1, np.int32)
            np.add.at(tail, np.maximum(offsets[1:] - LENGTH + 1, offsets[:-1]), 1)
            np.add.at(tail, offsets[1:], -1)
            again = ~first & (np.cumsum(tail)[:-1] == 0)
            step = np.diff(again.astype(np.int8), prepend=0, append=0)
            edge = np.zeros(total + 1, np.int32)
            np.add.at(edge, np.flatnonzero(step == 1), 1)
            np.add.at(edge, np.flatnonzero(step == -1) + LENGTH - 1, -1)
            gone = np.cumsum(edge)[:-1] > 0
            count = np.concatenate([[0], np.cumsum(gone)])
            begin = gone.copy()
            begin[1:] &= ~gone[:-1]
            full = offsets[:-1][offsets[:-1] < offsets[1:]]
            begin[full] = gone[full]
            spans_ = np.concatenate([[0], np.cumsum(begin)])
            rest = []
            for k, doc_id in enumerate(ids):
                x, y = offsets[k], offsets[k + 1]
                kept = data[x:y] if count[y] == count[x] else data[x:y][~gone[x:y]]
                kept = kept.tobytes()
                if carried:
                    rest.append(kept.decode("utf-8", "ignore"))
                    continue
                out[0].append(None if doc_id == NO_ID else int(doc_id))
                out[1].append(int(y - x))
                out[2].append(int(count[y] - count[x]))
                out[3].append(int(spans_[y] - spans_[x]))
                out[4].append(hashlib.sha256(kept).hexdigest())
            if carried:
                held = pa.ipc.open_stream(zstandard.ZstdDecompressor().decompress(other)).read_all()
                tables.append(held.append_column("kept_text", pa.array(rest, pa.string())))
        release()
        if carried:
            return pa.concat_tables(tables) if tables else pa.table({c: pa.nulls(0) for c in [*carried, "kept_text"]})
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string())
        return pa.table([pa.array(x, t) for x, t in zip(out, kinds)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return kernel


def _plan(df: DataFrame, carried: list[str], schema) -> DataFrame:
    parts = parts_for(df, PART_BYTES)
    keys = df.select("doc_id", "text")
    runs = keys.mapInArrow(freeing(_anchor_rows(parts)), BLOB).repartitionById(parts, "part")
    decided = runs.mapInArrow(freeing(_decide_runs(parts)), BLOB)
    held = df.mapInArrow(freeing(_text_rows(parts)), BLOB).unionByName(decided)
    strings = held.groupBy("part").applyInArrow(_open_strings(parts), BLOB).repartitionById(parts, "part")
    firsts = strings.mapInArrow(freeing(_decide_strings(parts)), BLOB)
    return held.groupBy("part").cogroup(firsts.groupBy("part")).applyInArrow(_remove(carried), schema)


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for every row."""
    df = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return _plan(df, [], "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string")


def cleaned_documents(docs: DataFrame) -> DataFrame:
    """The documents with their repeated bytes cut out; cut characters go whole. Other columns travel with the text."""
    from pyspark.sql import types as T

    other = [c for c in docs.columns if c not in ("text", "n_chars")]
    carried = [f"c{k}" for k in range(len(other))]
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text"), *[F.col(f"`{c}`").alias(n) for c, n in zip(other, carried)])
    schema = T.StructType([T.StructField(n, df.schema[n].dataType) for n in carried] + [T.StructField("kept_text", T.StringType())])
    got = _plan(df, carried, schema)
    new = {"text": F.col("kept_text"), "n_chars": F.length("kept_text").cast("long")} | {c: F.col(n) for c, n in zip(other, carried)}
    return got.select(*[new[c].alias(c) for c in docs.columns])
