"""Token ids of whole texts, each distinct word of a block encoded once.

The tokenizer drops white space and never joins across it, nor across a border between a letter and an ASCII
mark or digit. So a block of texts is split at white space, its distinct pieces at such borders, and only
words that the worker has not met go through the library; ids are then gathered by position. Texts that hold
the start of a special token's name go through the library whole, and so does everything if the tokenizer
file has other rules than RULES.

Defined cases: a null text has no ids, as an empty one; a long text is worked on in slices that end at white space.
"""

from __future__ import annotations

import json
import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import slices, spans, utf8

#: Words that a worker remembers; beyond it, those of the last block stay.
CACHE = 600_000
#: Bytes of text in a block.
BLOCK = 8 << 20
FILE = "word_bpe_49k.json"

# The rules of the tokenizer file for which splitting is exact.
RULES = {
    "normalizer": ["NFC", "Replace", "Lowercase"],
    "pattern": "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+",
    "white space": "\\s+",
    "behaviour": ("Removed", True),
}
# Fixed values of byte-level BPE: printable bytes stand for themselves, the others for code points from 256 on.
_PRINTED = [*range(33, 127), *range(161, 173), *range(174, 256)]
_BYTE_CHARS = {b: b for b in _PRINTED} | {b: 256 + k for k, b in enumerate(b for b in range(256) if b not in _PRINTED)}

_OTHER, _LETTER, _MARK, _DIGIT = range(4)
_KIND = np.zeros(256, np.uint8)
_KIND[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = _MARK
_KIND[ord("'")] = _OTHER  # it may begin a suffix
_KIND[48:58] = _DIGIT
_KIND[[*range(65, 91), *range(97, 123)]] = _LETTER
#: First bytes of two-byte letters: Latin up to U+02AF, Cyrillic up to U+047F.
_LEAD = np.zeros(256, bool)
_LEAD[[*range(0xC3, 0xCB), 0xD0, 0xD1]] = True
#: Lower-case Latin letters that normal form and lower-casing leave alone.
_PLAIN = re.compile("[a-zß-öø-ÿ]+").fullmatch


def borders(data: np.ndarray) -> np.ndarray:
    """Places of the UTF-8 bytes before which a word ends for sure, whatever stands around."""
    kind = _KIND[data]
    ends = kind.copy()  # of the character that ends at a byte; kind is that of the one that begins there
    at = np.flatnonzero(_LEAD[data[:-1]]) if len(data) else np.zeros(0, np.int64)
    pair = data[at].astype(np.int64) << 8 | data[at + 1]
    at = at[(pair != 0xC397) & (pair != 0xC3B7) & (pair < 0xCAB0) | (pair > 0xCFFF)]
    kind[at], ends[at + 1] = _LETTER, _LETTER
    ends[at[(data[at] == 0xC4) & (data[at + 1] == 0xB0)] + 1] = _OTHER  # its lower case ends with a mark of its own
    before, after = ends[:-1], kind[1:]
    return np.flatnonzero((before > 0) & (after > 0) & ((before != after) | (before == _DIGIT))) + 1


def _exact(path: str) -> bool:
    with open(path, encoding="utf-8") as f:
        told = json.load(f)
    steps, first = (told.get("normalizer") or {}).get("normalizers") or [], (told.get("pre_tokenizer") or {}).get("pretokenizers") or [{}]
    blank = [s for s in steps if s["type"] == "Replace"]
    rules = {
        "normalizer": [s["type"] for s in steps],
        "pattern": (first[0].get("pattern") or {}).get("Regex"),
        "white space": blank[0]["pattern"].get("Regex") if blank else None,
        "behaviour": (first[0].get("behavior"), first[0].get("invert")),
    }
    last = first[-1]
    plain = last.get("type") == "ByteLevel" and not last.get("add_prefix_space") and not last.get("use_regex") and len(first) == 2
    names = [t["content"] for t in told.get("added_tokens", [])]
    return rules == RULES and plain and told.get("post_processor") is None and all(x.startswith("<|") for x in names)


class Coder:
    """Ids of texts; kept by the worker, with the words it has met."""

    def __init__(self, path: str, cache: int):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok, self.cache, self.exact = Tokenizer.from_file(path), cache, _exact(path)
        self.kind = np.uint16 if self.tok.get_vocab_size() <= 1 << 16 else np.uint32
        self._forget()

    def _forget(self) -> None:
        self.slots: dict[str, int] = {}
        self.sizes, self.ids = [np.zeros(0, np.int64)], [np.zeros(0, self.kind)]

    def library(self, text: bytes) -> np.ndarray:
        return np.array(self.tok.encode(text.decode(), add_special_tokens=False).ids, self.kind)

    def _learn(self, words: list[str]) -> None:
        """Ids of words that are not known yet."""
        tokenize, plain, rest, ids, ends = self.tok.model.tokenize, [], [], [], []
        for word in words:
            if not _PLAIN(word):
                rest.append(word)
                continue
            form = word if word.isascii() else word.encode().decode("latin-1").translate(_BYTE_CHARS)
            ids += [t.id for t in tokenize(form)]
            plain.append(word)
            ends.append(len(ids))
        sizes = [np.diff(np.array(ends, np.int64), prepend=0)]
        for a in range(0, len(rest), 4096):
            part = rest[a : a + 4096]
            e = self.tok.encode(part, is_pretokenized=True, add_special_tokens=False)
            sizes.append(np.bincount(np.array(e.word_ids, np.int64), minlength=len(part)))
            ids += e.ids
        self.slots.update(zip([*plain, *rest], range(len(self.slots), len(self.slots) + len(words))))
        self.sizes.append(np.concatenate(sizes))
        self.ids.append(np.array(ids, self.kind))

    def _known(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Slots of the words; first place and number of ids of every slot."""
        if len(self.slots) > self.cache:
            self._forget()
        found = [*map(self.slots.get, words)]
        new = [x for x, s in zip(words, found) if s is None]
        if new:
            self._learn(new)
            later = map(self.slots.__getitem__, new)
            found = [next(later) if s is None else s for s in found]
            self.sizes, self.ids = [np.concatenate(self.sizes)], [np.concatenate(self.ids)]
        return np.array(found, np.int64), np.cumsum(self.sizes[0]) - self.sizes[0], self.sizes[0]

    def _block(self, data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts of a block in a row, and their number for each text."""
        raw, special = data.tobytes(), []
        low = np.frombuffer(raw.lower(), np.uint8)
        # Capitals followed by combining marks may meet another normal form when lower-cased first.
        if b"<|" in raw or b"\xcc" in raw or b"\xcd" in raw:
            low = low.copy()
            for k, (a, b) in enumerate(zip(at.tolist(), at[1:].tolist())):
                if raw.find(b"<|", a, b) >= 0:
                    low[a:b] = 32
                    special.append(k)
                elif raw.find(b"\xcc", a, b) >= 0 or raw.find(b"\xcd", a, b) >= 0:
                    low[a:b] = data[a:b]
        texts = pa.StringArray.from_buffers(len(at) - 1, pa.py_buffer(at.astype(np.int32)), pa.py_buffer(low))
        split = pc.ascii_split_whitespace(texts)
        pieces = split.flatten().dictionary_encode()
        first, letters = split.offsets.to_numpy(), pieces.dictionary
        if not len(letters):
            return self._with(special, raw, at, np.zeros(0, self.kind), np.zeros(len(at) - 1, np.int64))
        # Distinct pieces, cut at borders: the same bytes under more offsets.
        seen, ends = utf8(letters)
        flag = np.zeros(len(seen) + 1, bool)
        flag[ends], flag[borders(seen)] = True, True
        cut = np.flatnonzero(flag)
        words = pa.StringArray.from_buffers(len(cut) - 1, pa.py_buffer(cut.astype(np.int32)), pa.py_buffer(seen)).dictionary_encode()
        line = pc.binary_join(pa.ListArray.from_arrays(pa.array([0, len(words.dictionary)], pa.int32()), words.dictionary), " ")
        slots, begin, size = self._known(line[0].as_py().split(" "))
        flat = self.ids[0]
        # Ids of the distinct pieces in a row; an empty piece has no bytes and no words.
        word = slots[words.indices.to_numpy()]
        own = flat[_ranges(begin[word], size[word])]
        total = np.concatenate([[0], np.cumsum(size[word])])[np.searchsorted(cut, ends)]
        piece = pieces.indices.to_numpy()
        number = np.diff(total)[piece]
        ids = own[_ranges(total[:-1][piece], number)]
        till = np.concatenate([[0], np.cumsum(number)])[first - first[0]]
        return self._with(special, raw, at, ids, np.diff(till))

    def _with(self, special: list[int], raw: bytes, at: np.ndarray, ids: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not special:
            return ids, sizes
        ends = np.cumsum(sizes)
        parts, done = [], 0
        for k in special:
            parts += [ids[done : ends[k]], self.library(raw[at[k] : at[k + 1]])]
            sizes[k] = len(parts[-1])
            done = ends[k]
        return np.concatenate([*parts, ids[done:]]), sizes

    def __call__(self, column: pa.Array) -> Iterator[np.ndarray]:
        """The ids of each row's text, row by row."""
        data, at = utf8(column)
        for a, b in spans(at, BLOCK):
            part = data[at[a] : at[b]]
            if not self.exact:
                for k in range(a, b):
                    yield self.library(data[at[k] : at[k + 1]].tobytes())
            elif len(part) > BLOCK and b"<|" in (raw := part.tobytes()):
                yield self.library(raw)
            elif len(part) > BLOCK:
                yield np.concatenate([self._block(part[x:y], np.array([0, y - x]))[0] for x, y in slices(part, BLOCK)])
            else:
                ids, sizes = self._block(part, at[a : b + 1] - at[a])
                ends = np.cumsum(sizes).tolist()
                yield from (ids[x:y] for x, y in zip([0, *ends], ends))

    def shrink(self, keep: int) -> None:
        """Forget all words if there are more than `keep`."""
        if len(self.slots) > keep:
            self._forget()


def _ranges(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """begin, begin + 1, ... of each range, one range after the other."""
    ends = np.cumsum(size)
    return np.repeat(begin - ends + size, size) + np.arange(ends[-1] if len(ends) else 0)


_coders: dict[str, Coder] = {}


def coder(path: str, cache: int = CACHE) -> Coder:
    """The worker's coder for the tokenizer file."""
    if path not in _coders:
        _coders[path] = Coder(path, cache)
    _coders[path].cache = cache
    return _coders[path]


def tokenizer_path(name: str = FILE) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
