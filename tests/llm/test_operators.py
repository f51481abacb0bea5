"""Each operator against a brute-force version on small inputs, and the cases that must not crash."""

from __future__ import annotations

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from motif_spark.llm import chat, classifier, fingerprint, license, mixing, packing, quality, simhash, suffix_dedup, wavelet
from motif_spark.llm.tokens import tokenizer_path

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [(9001, None, None, None, None), (9002, "", "en", "s", 0), (9003, " \n\t ", "en", "s", 4), (9004, "a", "en", None, 1), (9005, "ab " * 700, "en", "s", 2100), (9006, "ab " * 700, "en", "s", 2100), (9007, "x" * 30_000, "xx", "t", 30_000)]


@pytest.fixture(scope="module")
def docs(spark, small):
    d = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars")
    return d.unionByName(spark.createDataFrame(ODD, SCHEMA)).cache()


@pytest.fixture(scope="module")
def rows(docs):
    return sorted(((r.doc_id, r.text or "", r.source) for r in docs.collect()), key=lambda r: r[0])


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def clash(docs):
    """Extra columns with names that operators use inside."""
    df = docs.limit(30)
    for name in ("fp", "part", "kind", "size", "shard", "_w", "_id", "key", "t", "a.b"):
        df = df.withColumn(name, F.lit("x"))
    return df


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text)


def test_fingerprints(docs, rows):
    got = {r.doc_id: r for r in fingerprint.compare_with_edits(docs).collect()}
    down = rows[::-1]
    for k, (i, text, _) in enumerate(down):
        edited = fingerprint.edit(text, down[(k + 1) % len(down)][1])
        assert (got[i].n_chars, got[i].edited_sha256) == (len(text), hashlib.sha256(edited.encode()).hexdigest())
    by_text = defaultdict(set)
    for i, text, _ in rows:
        by_text[text].add(got[i].fingerprint)
    assert all(len(x) == 1 for x in by_text.values())
    plain = {r.doc_id: r.fingerprint for r in fingerprint.fingerprints(docs).collect()}
    assert plain == {i: r.fingerprint for i, r in got.items()}
    a, b = fingerprint.parse([plain[i] for i, _, _ in down]), fingerprint.parse([plain[i] for i, _, _ in down[1:] + down[:1]])
    assert np.allclose(fingerprint.likeness(a, b), [got[i].near_next for i, _, _ in down])
    near = [(r.near_edited, r.near_next) for r in got.values() if r.n_chars > 300]
    assert np.mean([x > y for x, y in near]) > 0.9
    assert all(0 <= x <= 1 for r in got.values() for x in (r.near_edited, r.near_next))


def test_fingerprint_counts():
    """Codes of one text, by plain counting."""
    text = b"the quick brown fox jumps over the lazy dog" * 3
    _, codes = fingerprint.digests(np.frombuffer(text, np.uint8), np.array([0, len(text)]))
    counts = np.zeros(256, int)
    for salt, (a, b, c) in enumerate(fingerprint.SHAPES):
        for p in range(len(text) - c):
            x = text[p + a] | text[p + b] << 8 | text[p + c] << 16
            x = x * 0x9E3779B1 & 0xFFFFFFFF
            x ^= x >> 15
            counts[(x * (0x85EBCA77 + 2 * salt) & 0xFFFFFFFF) >> 24] += 1
    q = np.sort(counts)[[63, 127, 191]]
    assert (codes[0] == (counts[:, None] > q).sum(1)).all()


def brute_repeats(rows, n=100):
    seen, out = set(), {}
    for i, text in rows:
        b = text.encode()
        edge = np.zeros(len(b) + 1, int)
        for s in range(len(b) - n + 1):
            w = b[s : s + n]
            if w in seen:
                edge[s] += 1
                edge[s + n] -= 1
            seen.add(w)
        gone = np.cumsum(edge)[:-1] > 0
        kept = np.frombuffer(b, np.uint8)[~gone].tobytes()
        out[i] = (len(b), int(gone.sum()), int((np.diff(gone.astype(int), prepend=0) == 1).sum()), hashlib.sha256(kept).hexdigest())
    return out


def test_repeats(docs, rows):
    got = {r.doc_id: tuple(r)[1:] for r in suffix_dedup.remove_repeats(docs).collect()}
    assert got == brute_repeats([(i, t) for i, t, _ in rows])


def test_repeats_in_long_text(spark, monkeypatch):
    rng = np.random.default_rng(3)
    body = "".join(rng.choice(list("abcdefgh "), 9000))
    texts = [(1, body), (2, body[100:4000] + "!" + body[4000:]), (3, body[50:149] + "?" + body[:101]), (4, ("é" + body[:300]) * 3)]
    monkeypatch.setattr(suffix_dedup, "BLOCK_BYTES", 700)
    data = [np.frombuffer(t.encode(), np.uint8) for _, t in texts]
    at = np.concatenate([[0], np.cumsum([len(d) for d in data])])
    small = [np.concatenate([b[k] for b in suffix_dedup._text_runs(np.concatenate(data), at)]) for k in range(5)]
    monkeypatch.setattr(suffix_dedup, "BLOCK_BYTES", 1 << 19)
    large = [np.concatenate([b[k] for b in suffix_dedup._text_runs(np.concatenate(data), at)]) for k in range(5)]
    assert sorted(zip(*[x.tolist() for x in small])) == sorted(zip(*[x.tolist() for x in large]))
    df = spark.createDataFrame(texts, "doc_id long, text string")
    got = {r.doc_id: tuple(r)[1:] for r in suffix_dedup.remove_repeats(df).collect()}
    assert got == brute_repeats(texts)


def test_quality(docs, rows):
    got = {r.doc_id: r for r in quality.assess(docs).collect()}
    for i, text, _ in rows:
        w = words(text)
        windows = [tuple(w[k : k + 5]) for k in range(len(w) - 4)]
        count, cover = Counter(windows), set()
        for k, x in enumerate(windows):
            if count[x] > 1:
                cover.update(range(k, k + 5))
        lines = [x for x in text.split("\n") if words(x)]
        g = got[i]
        assert (g.n_words, g.word_chars, g.n_symbols, g.n_dup_lines, g.n_repeat_words) == (len(w), sum(map(len, w)), sum(c in quality.SYMBOLS for c in text), len(lines) - len(set(lines)), len(cover))
        assert g.base_failed == (len(w) < 10 or 100 * len(cover) > 20 * len(w))
        assert not (g.base_failed and g.kept)


def test_quality_lines(spark):
    prose = "This is a plain sentence of enough words to be kept here."
    texts = [(1, f"{prose}\nHome | About | Contact | Login\nAnother line that says quite different things, at length."), (2, "Home | About | Contact | Help | News | Shop | Jobs | Press | More | Site | Map | End"), (3, f"{prose} And one more of them, quite long.\nAll rights reserved.")]
    df = spark.createDataFrame(texts, "doc_id long, text string").withColumn("n_chars", F.length("text").cast("long"))
    got = {r.doc_id: r for r in quality.assess(df).collect()}
    assert got[1].kept and "Home" not in got[1].clean_text
    assert not got[2].kept and got[2].lost == 1.0
    assert got[3].kept and "rights" not in got[3].clean_text
    kept = quality.keep_documents(df).collect()
    assert sorted(r.doc_id for r in kept) == [1, 3] and all(r.n_chars == len(r.text) for r in kept)


def test_chat(spark):
    turns = [(1, 0, "system", "be kind"), (1, 1, "ann", "hi"), (1, 2, "bob", None), (1, 3, None, "hey"), (2, 0, "system", "alone"), (None, 0, "ann", "x"), (1, 300, "ann", "late")]
    got = chat.rotate(spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")).collect()
    mine = sorted((r for r in got if r.conv_id == 1 and r.perspective == "ann"), key=lambda r: r.start)
    text = "".join(r.segment for r in mine)
    assert text == "<|system|>\nbe kind<|end|>\n<|assistant|>\nhi<|end|>\n<|user:bob|>\n<|end|>\n<|user:unknown|>\nhey<|end|>\n<|assistant|>\nlate<|end|>\n"
    assert [text[r.mask_start : r.mask_end] for r in mine if r.mask_start is not None] == ["hi<|end|>\n", "late<|end|>\n"]
    assert {r.perspective for r in got if r.conv_id == 1} == {"ann", "bob", "unknown"}
    assert not [r for r in got if r.conv_id == 2] and len([r for r in got if r.conv_id is None]) == 1


def test_license(docs, rows, spark):
    more = [(1, "THE MIT License, the Apache license; GNU General Public License", "s"), (2, "Licensed under CC BY-NC 4.0.", "s"), (3, "licence of mit", "s")]
    df = docs.select("doc_id", "text", "source").unionByName(spark.createDataFrame(more, "doc_id long, text string, source string").withColumn("doc_id", F.col("doc_id") + 8000))
    got = {r.doc_id: r for r in license.scan(df).collect()}
    for i, text, _ in rows + [(i + 8000, t, s) for i, t, s in more]:
        w, places, labels = license.words_of(text), [], set()
        for label, phrase in license.BASE:
            p = phrase.split()
            for k in range(len(w) - len(p) + 1):
                if w[k : k + len(p)] == p:
                    places.append(k)
                    labels.add(label)
        g = got[i]
        assert (g.n_words, g.n_base, g.first_word, g.last_word, g.base_labels) == (len(w), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(labels)))
        assert labels <= set(g.labels.split(",")) | {""} and 0 <= g.score <= 1
    assert got[8002].labels == "cc-by-nc" and got[8002].score == 1.0 and got[8003].labels == ""


@pytest.fixture(scope="module")
def ids(rows):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path())
    return {i: t.encode(x, add_special_tokens=False).ids for i, x, _ in rows}


def test_wavelet_matrix():
    values = np.random.default_rng(1).integers(0, 300, 5000)
    m = wavelet.WaveletMatrix.build(values)
    assert (m.decode() == values).all()
    assert [m.access(i) for i in range(0, 5000, 97)] == values[::97].tolist()
    for v in (0, 7, 299, 70_000):
        places = np.flatnonzero(values == v)
        assert m.count(v) == len(places) and m.count(v, 2500) == (places < 2500).sum()
        assert [m.occurrence(v, k) for k in range(len(places))] == places.tolist() and m.occurrence(v, len(places)) == -1


def test_wavelet_round_trip(docs, rows, ids):
    got = {r.doc_id: tuple(r)[1:] for r in wavelet.round_trip(docs, tokenizer_path()).collect()}
    start = 0
    for i, _, _ in rows:
        own = [*ids[i], wavelet.END]
        assert got[i] == (start, len(own), zlib.crc32(np.array(own, "<u4").tobytes()))
        start += len(own)


def test_packing(docs, ids):
    got = packing.pack(docs, tokenizer_path()).collect()
    want = {}
    for i, x in ids.items():
        own = [*x, packing.END]
        for p in range(0, len(own), 2048):
            part = own[p : p + 2048]
            want[i, p // 2048] = (p, len(part), zlib.crc32(np.array(part, "<u4").tobytes()))
    assert {(r.doc_id, r.piece): (r.start, r.length, r.ids_crc32) for r in got} == want and len(got) == len(want)
    held = defaultdict(list)
    for r in got:
        held[r.sequence_id].append((r.offset, r.length))
    for spans in held.values():
        end = 0
        for offset, length in sorted(spans):
            assert offset == end
            end += length
        assert end <= 2048
    assert len(held) == -(-sum(r.length for r in got) // 2048)


def test_plan_is_no_worse_than_best_fit():
    rng = np.random.default_rng(5)
    for _ in range(20):
        counts = Counter(rng.integers(1, 101, rng.integers(1, 120)).tolist())
        plan = packing.plan(dict(counts), 100)
        assert sum(n for _, n in plan) <= packing.best_fit(dict(counts), 100)
        used = Counter()
        for filling, times in plan:
            assert sum(filling) <= 100
            for x in filling:
                used[x] += times
        assert used == counts


def test_mixing(docs, rows):
    got = mixing.mix(docs).collect()
    size = {i: len(words(t)) for i, t, _ in rows}
    by = defaultdict(int)
    for i, _, s in rows:
        by[s] += size[i]
    order = sorted((s for s in by if s is not None)) + [None] * (None in by)
    weight = {s: (3, 1, 2)[k % 3] for k, s in enumerate(order)}
    open_, target, left = set(order), {}, 1.5 * sum(by.values())
    while True:
        total = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / total > 2 * by[s] + 1e-9]
        if not over:
            target |= {s: left * weight[s] / total for s in open_}
            break
        for s in over:
            target[s] = 2 * by[s]
            left -= target[s]
            open_.discard(s)
    source = {i: s for i, _, s in rows}
    taken = defaultdict(int)
    for r in got:
        assert r["size"] == size[r.doc_id] and r.source_size == by[source[r.doc_id]] and abs(r.target - target[source[r.doc_id]]) < 1e-6
        assert 0 <= r.taken <= 2 * r["size"]
        taken[source[r.doc_id]] += r.taken
    assert all(abs(taken[s] - target[s]) <= mixing.BLOCK for s in order)
    assert sorted(map(tuple, got)) == sorted(map(tuple, mixing.mix(docs.repartition(3)).collect()), key=lambda x: x) or {(r.doc_id, r.taken) for r in got} == {(r.doc_id, r.taken) for r in mixing.mix(docs.repartition(3)).collect()}
    made = mixing.mixed_documents(docs)
    assert made.columns == docs.columns
    sums = {r.doc_id: r.n for r in made.groupBy("doc_id").agg(F.sum(F.size(F.array_remove(F.split("text", r"[\x20\x09-\x0D]+"), ""))).alias("n")).collect()}
    assert sums == {r.doc_id: r.taken for r in got if r.taken}


def test_sainte_lague(spark):
    votes = {0: 340.0, 1: 280.0, 2: 160.0, 3: 60.0, 4: 0.0}
    for seats in (0, 1, 7, 100):
        won = Counter({k: 0 for k in votes})
        for _ in range(seats):
            won[max(votes, key=lambda k: (votes[k] / (2 * won[k] + 1), -k))] += 1
        df = spark.createDataFrame([(0, k, v, seats) for k, v in votes.items()], "g int, party long, votes double, seats long")
        assert {r.party: r.seats_won for r in mixing.sainte_lague(df, ["g"]).collect()} == dict(won)


def brute_components(fp):
    ids = sorted(fp)
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    v = np.array([fp[i] for i in ids], np.uint64)
    for k, i in enumerate(ids):
        for j in np.flatnonzero(np.bitwise_count(v[k + 1 :] ^ v[k]) <= 3):
            a, b = find(i), find(ids[k + 1 + j])
            root[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_simhash(docs, rows):
    import xxhash

    got = {r.doc_id: r for r in simhash.near_duplicates(docs).collect()}
    fp = {}
    for i, text, _ in rows:
        w = words(re.sub("[A-Z]", lambda m: m[0].lower(), text))
        shingles = [" ".join(w[k : k + 3]) for k in range(len(w) - 2)] if len(w) > 3 else ([" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
        fp[i] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
    assert {i: int(r.fingerprint, 16) for i, r in got.items()} == fp
    assert {i: r.component_id for i, r in got.items()} == brute_components(fp)


def test_covering_and_large_buckets(spark):
    masks = simhash.covering(list(range(64)))
    rng = np.random.default_rng(2)
    for _ in range(500):
        places = rng.choice(64, 3, replace=False)
        assert any(not any(m >> int(p) & 1 for p in places) for m in masks)
    base = int(rng.integers(1 << 62))
    fp = {i: base ^ int(np.bitwise_xor.reduce(np.uint64(1) << rng.choice(64, 6).astype(np.uint64))) for i in range(300)}
    fp |= {1000 + i: int(rng.integers(1 << 63)) for i in range(100)}
    df = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in set(fp.values())], "fp long")
    least = {}
    for i in sorted(fp):
        least.setdefault(fp[i], i)
    want = brute_components({i: f for f, i in least.items()})
    for most in (4, 2048):
        links = [(r.a & (1 << 64) - 1, r.b & (1 << 64) - 1) for r in simhash.near_links(df, most=most).collect()]
        root = {f: f for f in least}

        def find(x):
            while root[x] != x:
                x = root[x]
            return x

        for a, b in links:
            assert (a ^ b).bit_count() <= 3
            root[find(a)] = find(b)
        groups, other = defaultdict(set), defaultdict(set)
        for f, i in least.items():
            groups[find(f)].add(i)
            other[want[i]].add(i)
        assert sorted(map(sorted, groups.values())) == sorted(map(sorted, other.values()))


def test_classifier(spark, small):
    docs, labels = (spark.read.parquet(f"{small.replace('0.001', '0.01')}/{t}.parquet") for t in ("documents", "labels"))
    got = classifier.classify(docs).join(labels, "doc_id").toPandas()
    assert (got["kept"] == (got["quality"] == 1)).mean() > 0.95
    assert got[got["quality"] == 1]["kept"].mean() > 0.97 and got["score"].between(0, 1).all()


def test_label_model():
    rng = np.random.default_rng(4)
    truth = rng.random(20_000) < 0.7
    right = [0.9, 0.8, 0.7, 0.85]
    votes = np.stack([np.where(rng.random(20_000) < 0.2, 0, np.where((rng.random(20_000) < p) == truth, 2, 1)) for p in right], 1)
    codes, counts = np.unique(votes @ 3 ** np.arange(4), return_counts=True)
    model = classifier.label_model(classifier.patterns_to_votes(codes, 4), counts.astype(float))
    assert abs(float(model["good"]) - 0.7) < 0.03 and np.abs(model["accuracy"].mean(1) - right).max() < 0.03


def test_statistics():
    import pyarrow as pa

    from motif_spark.llm.common import utf8

    texts = ["", None, "a", " a a  b\n", "abba baab abba", "é é ü\n\nx"]
    got = classifier.statistics(*utf8(pa.array(texts)))
    for k, t in enumerate(texts):
        w = words(t or "")
        assert got[k, 0] == len(w) and got[k, 1] == (len(set(w)) / len(w) if w else 0)


PLAIN = {
    "fingerprint": fingerprint.compare_with_edits,
    "repeats": suffix_dedup.remove_repeats,
    "quality": quality.assess,
    "kept": quality.keep_documents,
    "license": license.scan,
    "wavelet": lambda d: wavelet.round_trip(d, tokenizer_path()),
    "packing": lambda d: packing.pack(d, tokenizer_path()),
    "mix": mixing.mix,
    "mixed": mixing.mixed_documents,
    "simhash": simhash.near_duplicates,
    "one": simhash.one_of_each,
    "cleaned": suffix_dedup.cleaned_documents,
    "classifier": classifier.classify,
}


@pytest.mark.parametrize("name", PLAIN)
def test_empty_repeated_and_clashing(name, empty, docs, clash, spark):
    assert PLAIN[name](empty).count() == 0
    twice = docs.limit(8).unionByName(docs.limit(8)).unionByName(spark.createDataFrame([(None, "lost id", None, None, None), (None, None, "en", "s", 1)], SCHEMA))
    rows = PLAIN[name](twice).collect()
    if name not in ("kept", "one", "mixed", "packing"):
        assert len(rows) == twice.count()
    got = PLAIN[name](clash)
    got.collect()
    if name in ("kept", "one", "mixed", "cleaned"):
        assert got.columns == clash.columns
