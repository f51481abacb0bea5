"""SimHash fingerprints and near-duplicate components by covering locality-sensitive hashing.

A random vector of r + 1 bits is given to each of the 64 places; table v keeps the places whose vector has
an odd inner product with v. Any r places span less than the whole space, so for each pair within r bits
some v is orthogonal to all the places that differ: the pair meets in that table, with certainty.

Defined cases: null, empty and wordless texts have fingerprint zero and are linked like any other;
repeated rows and ids are kept, each with its component; null ids are passed over for the smallest id; an empty
table gives an empty result; a very long text is hashed in blocks of its shingles; a bit that exactly half of the
shingles have is 0; extra columns are left out, but one_of_each() keeps them.
"""

from __future__ import annotations

import random
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpoint, freeing, spans, utf8

RADIUS = 3
#: Share of five-word shingles that near copies have in common, and the bands and rows of least hashes that
#: find candidates: two texts at the share miss all bands with probability (1 - 0.8^5)^24, below 0.0001.
ALIKE, BANDS, ROWS = 0.8, 24, 5
#: Buckets of more fingerprints are divided by a second covering of the places that the first left out.
BUCKET = 2_048
SPACES = b" \t\n\x0b\x0c\r"


def covering(places: list[int], radius: int = RADIUS, seed: int = 11) -> list[int]:
    """2^(radius+1) - 1 masks over the given places, such that any `radius` of them miss some mask."""
    rng, order = random.Random(seed), list(places)
    rng.shuffle(order)
    vectors = list(range(1, 2 ** (radius + 1)))
    given = {place: vectors[k % len(vectors)] for k, place in enumerate(order)}
    return [sum(1 << place for place, x in given.items() if (x & v).bit_count() % 2) for v in vectors]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def fingerprint(words: list[bytes], width: int = 3) -> int:
    """64 bits: those set in over half of the shingles' XXH64, repeats counted."""
    return int(_bits(_hashes(words, width)))


def _hashes(words: list[bytes], width: int) -> np.ndarray:
    import xxhash

    if len(words) > width:
        texts = [a + b" " + b + b" " + c for a, b, c in zip(words, words[1:], words[2:])] if width == 3 else [b" ".join(words[k : k + width]) for k in range(len(words) - width + 1)]
    else:
        texts = [b" ".join(words)] if words else []
    one = xxhash.xxh64_intdigest
    return np.fromiter((one(x, 42) for x in texts), np.uint64, len(texts))


def _bits(h: np.ndarray) -> np.uint64:
    if not len(h):
        return np.uint64(0)
    counts = np.zeros(64, np.int64)
    for k in range(0, len(h), 4096):
        counts += np.unpackbits(h[k : k + 4096].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int32)
    return np.packbits(2 * counts > len(h)).view(">u8")[0].astype(np.uint64)


def fingerprints(docs: DataFrame, width: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and fp (a signed long with the fingerprint's bits) for every row."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(1))
            out = np.zeros(batch.num_rows, np.uint64)
            for a, b in spans(offsets, 1 << 20):
                block = data[offsets[a] : offsets[b]].tobytes().lower()
                for k in range(a, b):
                    out[k] = _bits(_hashes(block[offsets[k] - offsets[a] : offsets[k + 1] - offsets[a]].split(), width))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out.view(np.int64))], ["doc_id", "fp"])

    kind = dict(docs.dtypes)[id_col]
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col)).mapInArrow(freeing(kernel), f"doc_id {kind}, fp bigint")


def _tables(df: DataFrame, masks: list[int]) -> DataFrame:
    pairs = F.array(*[F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("key")) for t, m in enumerate(masks)])
    return df.withColumn("_x", F.explode(pairs)).select("*", "_x.t", "_x.key").drop("_x")


def _forest(values: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links of a spanning forest of the fingerprints within the radius, breadth first over what is unvisited."""
    left, a, b = values[1:], [], []
    front = [values[0]] if len(values) else []
    while len(left):
        if not front:
            front, left = [left[0]], left[1:]
            continue
        x = front.pop()
        near = np.bitwise_count(left ^ x) <= radius
        if near.any():
            got = left[near]
            a.append(np.full(len(got), x)), b.append(got)
            front.extend(got)
            left = left[~near]
    none = np.zeros(0, np.uint64)
    return (np.concatenate(a), np.concatenate(b)) if a else (none, none)


def _links(buckets: DataFrame, keys: list[str], radius: int) -> DataFrame:
    """Spanning links within each bucket; buckets arrive sorted, one batch after the other."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[np.ndarray] = []

        def out(groups: np.ndarray) -> pa.RecordBatch:
            ends = [0, *(np.flatnonzero((groups[1:, :-1] != groups[:-1, :-1]).any(1)) + 1), len(groups)]
            found = [_forest(groups[a:b, -1].astype(np.uint64), radius) for a, b in zip(ends, ends[1:]) if b - a > 1]
            cols = [np.concatenate([f[k] for f in found]) if found else np.zeros(0, np.uint64) for k in (0, 1)]
            return pa.RecordBatch.from_arrays([pa.array(c.view(np.int64)) for c in cols], ["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            rows = np.stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in batch.columns], 1).view(np.uint64)
            rows = np.concatenate([*kept, rows])
            last = np.flatnonzero((rows[:, :-1] != rows[-1, :-1]).any(1))
            cut = last[-1] + 1 if len(last) else 0
            if cut:
                yield out(rows[:cut])
            kept = [rows[cut:]]
        if kept:
            yield out(kept[0])

    df = buckets.select(*keys, "fp").repartition(*keys).sortWithinPartitions(*keys)
    return df.mapInArrow(kernel, "a bigint, b bigint")


def near_links(distinct: DataFrame, radius: int = RADIUS, most: int = BUCKET) -> DataFrame:
    """Links (a, b) of distinct fingerprints that join all and only those connected within the radius.

    Tables whose buckets hold over `most` are covered again on the places that the bucket leaves free; a
    third round leaves at most some 8 free bits, so no bucket can hold more than a few hundred after it.
    """
    first = covering(list(range(64)), radius)
    level = _tables(distinct, first)
    counts = level.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > 1)
    counts = checkpoint(counts.filter(F.col("n") > most))
    links = _links(level.join(counts, ["t", "key"], "left_anti"), ["t", "key"], radius)
    if counts.isEmpty():
        return links
    big = level.join(counts.select("t", "key"), ["t", "key"], "left_semi")
    found = [links]
    free = {t: [p for p in range(64) if not m >> p & 1] for t, m in enumerate(first)}
    for t in sorted(r["t"] for r in counts.select("t").distinct().collect()):
        part = big.filter(F.col("t") == t).select("fp", F.col("key").alias("k1"))
        second = covering(free[t], radius, 100 + t)
        for u, m in enumerate(second):
            rest = [p for p in free[t] if not m >> p & 1]
            cut = part.withColumn("k2", F.col("fp").bitwiseAND(F.lit(_signed(m))))
            deep = covering(rest, radius, 1000 + u) if len(rest) > 4 else [0]
            last = _tables(cut, deep).withColumn("u", F.lit(t * 64 + u))
            found.append(last.select("u", "t", "k1", "k2", "key", "fp"))
    tail = found[1]
    for x in found[2:]:
        tail = tail.unionByName(x)
    return links.unionByName(_links(tail, ["u", "t", "k1", "k2", "key"], radius))


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """id, root: the smallest id reachable, for every id in the links. Alternates large-star and small-star.

    Each round is two aggregations by node; the smallest neighbour is found by a partial aggregation, and
    hubs lose their links to it, so no list of neighbours is ever gathered.
    """
    edges = checkpoint(links.filter("a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    before = None
    for _ in range(rounds):
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("a", "m"))
        large = both.join(least, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        star = large.join(least, "a")
        small = star.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(star.select("a", F.col("m").alias("b"))).filter("a != b").distinct()
        edges = checkpoint(small)
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    roots = edges.select(F.col("b").alias("id")).distinct()
    return edges.select(F.col("a").alias("id"), F.col("b").alias("root")).unionByName(roots.select("id", F.col("id").alias("root")))


def near_duplicates(docs: DataFrame, radius: int = RADIUS, width: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable) for every row."""
    fps = checkpoint(fingerprints(docs, width, id_col, text_col))
    groups = checkpoint(fps.groupBy("fp").agg(F.min("doc_id").alias("least")))
    roots = components(near_links(groups.select("fp"), radius))
    held = groups.join(roots, F.col("fp") == F.col("id"), "left").withColumn("root", F.coalesce("root", "fp"))
    named = held.groupBy("root").agg(F.min("least").alias("component_id"))
    by_fp = held.select("fp", "root").join(named, "root").select("fp", "component_id")
    return fps.join(by_fp, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


_ODD = np.random.default_rng(17).integers(0, 1 << 63, BANDS * ROWS).astype(np.uint64) * np.uint64(2) + np.uint64(1)
_FLIP = np.random.default_rng(18).integers(0, 1 << 63, BANDS * ROWS).astype(np.uint64)
_MIX = np.uint64(0x9E3779B97F4A7C15)


def shingle_set(words: list[bytes]) -> np.ndarray:
    """Sorted distinct 64-bit names of the five-word shingles, each made of its first and last three words."""
    return _fives(_hashes(words, 3)) if len(words) > 4 else np.zeros(0, np.uint64)


def _fives(threes: np.ndarray) -> np.ndarray:
    h = threes[:-2] * _MIX ^ (threes[2:] >> np.uint64(29) | threes[2:] << np.uint64(35))
    h = (h ^ h >> np.uint64(32)) * _MIX
    return np.unique(h ^ h >> np.uint64(29))


def _bands(shingles: np.ndarray) -> np.ndarray:
    """A key for each band: that of its least hashes."""
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for k in range(0, len(shingles), 2048):
        least = np.minimum(least, ((shingles[k : k + 2048] ^ _FLIP[:, None]) * _ODD[:, None]).min(1))
    keys = np.zeros(BANDS, np.uint64)
    for column in least.reshape(BANDS, ROWS).T:
        keys = (keys ^ column) * _MIX
        keys ^= keys >> np.uint64(31)
    return keys


def _texts(batch: pa.RecordBatch) -> Iterator[tuple[int, list[bytes]]]:
    """Row and lower-case words of each text in column 1."""
    data, offsets = utf8(batch.column(1))
    for a, b in spans(offsets, 1 << 20):
        block = data[offsets[a] : offsets[b]].tobytes().lower()
        for k in range(a, b):
            yield k, block[offsets[k] - offsets[a] : offsets[k + 1] - offsets[a]].split()


def profiles(rows: DataFrame, width: int = 3) -> DataFrame:
    """row, fp and the band keys (none below five words) of rows with columns row and text."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out, keys, ends = np.zeros(batch.num_rows, np.uint64), [], [0]
            for k, words in _texts(batch):
                threes = _hashes(words, 3)
                out[k] = _bits(threes if width == 3 else _hashes(words, width))
                if len(words) > 4:
                    keys.append(_bands(_fives(threes)))
                ends.append(len(keys) * BANDS)
            flat = np.concatenate(keys) if keys else np.zeros(0, np.uint64)
            bands = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat.view(np.int64)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out.view(np.int64)), bands], ["row", "fp", "bands"])

    return rows.select("row", "text").mapInArrow(freeing(kernel), f"row {dict(rows.dtypes)['row']}, fp bigint, bands array<bigint>")


def _shingles(rows: DataFrame) -> DataFrame:
    """name and shingles (8 bytes each, sorted) of rows with columns name and text."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingle_set(words).tobytes() for _, words in _texts(batch)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.binary())], ["name", "shingles"])

    return rows.select("name", "text").mapInArrow(freeing(kernel), "name bigint, shingles binary")


def alike_forest(sets: list[np.ndarray], share: float = ALIKE) -> list[tuple[int, int]]:
    """Links that join all and only the sets connected by pairs with at least `share` in common, exactly."""
    sizes, left, front, links = np.array([len(x) for x in sets]), np.arange(1, len(sets)), [0], []
    while len(left):
        if not front:
            front, left = [int(left[0])], left[1:]
            continue
        x = front.pop()
        near = left[np.minimum(sizes[left], sizes[x]) >= share * np.maximum(sizes[left], sizes[x]) - 1e-9]
        if not len(near):
            continue
        flat = np.concatenate([sets[y] for y in near])
        at = np.minimum(np.searchsorted(sets[x], flat), sizes[x] - 1)
        ends = np.concatenate([[0], np.cumsum(sizes[near])[:-1]])
        common = np.add.reduceat((sets[x][at] == flat).astype(np.int64), ends)
        got = near[common >= share * (sizes[near] + sizes[x] - common) - 1e-9]
        if len(got):
            links += [(x, int(y)) for y in got]
            front += got.tolist()
            left = np.setdiff1d(left, got, assume_unique=True)
    return links


def copy_links(texts: DataFrame, rows: DataFrame, share: float = ALIKE) -> DataFrame:
    """Links (a, b) of fingerprints of texts whose five-word shingles are alike by the share.

    texts has name, fp and bands of distinct texts, rows name and text. Texts that share a band key are
    compared by their whole shingle sets; of bands with the same texts, one is looked at.
    """
    level = texts.select("name", "fp", F.posexplode("bands").alias("t", "key"))
    shared = level.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n"), F.min("name").alias("lo"), F.max("name").alias("hi"), F.bit_xor(F.xxhash64("name")).alias("x"))
    chosen = shared.filter("n > 1").groupBy("n", "lo", "hi", "x").agg(F.min(F.struct("t", "key")).alias("b")).select("b.t", "b.key")
    members = checkpoint(level.join(chosen, ["t", "key"]))
    sets = _shingles(rows.join(members.select("name").distinct(), "name", "left_semi")).dropDuplicates(["name"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, fps, sets = None, [], []

        def out() -> pa.RecordBatch:
            found = alike_forest(sets, share) if len(sets) > 1 else []
            cols = [pa.array([fps[link[k]] for link in found], pa.int64()) for k in (0, 1)]
            return pa.RecordBatch.from_arrays(cols, ["a", "b"])

        for batch in batches:
            for t, k, fp, data in zip(*[batch.column(c).to_pylist() for c in range(3)], batch.column(3)):
                if (t, k) != key:
                    yield out()
                    key, fps, sets = (t, k), [], []
                fps.append(fp), sets.append(np.frombuffer(data.as_py(), np.uint64))
        yield out()

    held = members.join(sets, "name").select("t", "key", "fp", "shingles").repartition("t", "key").sortWithinPartitions("t", "key")
    return held.mapInArrow(freeing(kernel), "a bigint, b bigint")


def one_of_each(docs: DataFrame, radius: int = RADIUS, width: int = 3) -> DataFrame:
    """One row of each group of near copies: that of the smallest id (null ids last), then of the smallest text name.

    Near copies are texts with fingerprints within the radius, or with ALIKE of their five-word shingles in
    common. Groups are of texts, so rows with a null or shared id stay apart unless their texts are near
    copies. Texts are named by 64 bits of their content.
    """
    name = F.xxhash64(F.coalesce("text", F.lit("")))
    rows = docs.select(F.struct(F.col("doc_id").alias("id"), name.alias("name")).alias("row"), "text")
    fps = checkpoint(profiles(rows, width)).select("row.id", "row.name", "fp", "bands")
    texts = checkpoint(fps.filter(F.size("bands") > 0).dropDuplicates(["name"]).select("name", "fp", "bands"))
    links = near_links(fps.select("fp").distinct(), radius).unionByName(copy_links(texts, docs.select(name.alias("name"), "text")))
    return _first_of_each(docs, name, fps.select("id", "name", "fp"), components(links))


def _first_of_each(docs: DataFrame, name: Column, fps: DataFrame, roots: DataFrame) -> DataFrame:
    roots = roots.select(F.col("id").alias("fp"), "root")
    held = fps.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    least = held.groupBy("root").agg(F.min(F.struct(F.col("id").isNull().alias("lost"), "id", "name")).alias("x"))
    keep = least.select(F.col("x.id").alias("__id"), F.col("x.name").alias("__name"))
    kept = docs.join(keep, F.col("doc_id").eqNullSafe(F.col("__id")) & (name == F.col("__name")), "left_semi")
    content = [F.col(f"`{c}`") for c, kind in docs.dtypes if "map<" not in kind]
    first = F.row_number().over(Window.partitionBy("doc_id", name).orderBy(F.xxhash64(*content)))
    return kept.withColumn("__first", first).filter("__first = 1").drop("__first")
