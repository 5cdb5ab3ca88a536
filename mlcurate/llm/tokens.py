"""Cached encoding of whole texts with the public word-BPE vocabulary.

Texts are lower-cased, cut at white space and put in a dictionary by Arrow's kernels, a
bounded slice of a batch at a time. Each distinct chunk is encoded once per worker, and
every occurrence is a gather from a table of ids. A text that holds a character outside
the range where these kernels' and the tokenizer's normalisation are known to agree
goes to the library as a whole.
"""

from __future__ import annotations

import gc
import json
import re
from dataclasses import dataclass

import numpy as np

#: Chunks held per worker before the table starts anew (bounds a worker's memory, as do ``MAX_CHARS``).
MAX_CHUNKS, MAX_CHARS = 500_000, 16_000_000
#: Last code point of the plain range.
_LAST = 0x24F

_PIECE = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zªµºß-öø-ɏ]+|[0-9²³¹¼½¾]|[^\s0-9a-zªµºß-öø-ɏ²³¹¼½¾]+")


def _plain_class() -> str:
    """Character class of what is plain: up to ``_LAST`` both as it is and in lower case, and no separator that only Python takes for white space."""
    ok = [c for c in range(_LAST + 1) if not 0x1C <= c <= 0x1F and len(chr(c).lower()) == 1 and ord(chr(c).lower()) <= _LAST]
    runs: list[list[int]] = []
    for c in ok:
        if runs and runs[-1][1] == c - 1:
            runs[-1][1] = c
        else:
            runs.append([c, c])
    return "".join(f"\\x{{{x:x}}}-\\x{{{y:x}}}" for x, y in runs)


_ODD = f"[^{_plain_class()}]|<\\|(?:start|end)oftext\\|>"


def default_path() -> str:
    """Place of the public vocabulary file."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def pieces(chunk: str) -> list[str]:
    """The pre-tokenizer's pieces of one lower-cased chunk without white space."""
    return _PIECE.findall(chunk)


class LibraryEncoder:
    """Distinct pieces through the tokenizers library; ``text_ids`` for whole texts."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.lib = Tokenizer.from_file(path)
        self.lib.no_padding()
        self.lib.no_truncation()
        size = self.lib.get_vocab_size(with_added_tokens=True)
        self.tokens = [self.lib.id_to_token(i) for i in range(size)]
        self.ends = np.array([t.endswith("</w>") for t in self.tokens])

    def text_ids(self, text: str) -> list[int]:
        return self.lib.encode(text, add_special_tokens=False).ids

    def many(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words, one after the other, and how many each has. Words go in by the hundred, joined by spaces, and come apart after each word-end token."""
        groups = [words[i : i + 200] for i in range(0, len(words), 200)]
        ids, lens = [np.zeros(0, np.uint16)], [np.zeros(0, np.int64)]
        for group, e in zip(groups, self.lib.encode_batch_fast([" ".join(g) for g in groups], add_special_tokens=False), strict=True):
            got = np.array(e.ids, np.uint16)
            n = np.diff(np.flatnonzero(self.ends[got]), prepend=-1)
            if len(n) != len(group):
                each = [self.text_ids(w) for w in group]
                got, n = np.array(sum(each, []), np.uint16), np.array([len(x) for x in each])
            ids.append(got)
            lens.append(n)
        return np.concatenate(ids), np.concatenate(lens)


@dataclass
class Batch:
    """Encoded texts: ``ids`` one text after the other, ``lens`` of each, the rows of their chunks with ``edges`` between texts, and the texts that the library took."""

    ids: np.ndarray
    lens: np.ndarray
    rows: np.ndarray
    edges: np.ndarray
    odd: list[int]


class ChunkTable:
    """chunk -> row of a growing pool of ids (and, on demand, its decoded text)."""

    def __init__(self, encoder, decoded: bool = False):
        self.encoder, self.decoded = encoder, decoded
        self._clear()

    def _clear(self) -> None:
        self.index: dict[str, int] = {}
        self.pool, self.start, self.length = np.zeros(1 << 16, np.uint16), np.zeros(1 << 14, np.int64), np.zeros(1 << 14, np.int32)
        self.used, self.chars, self.said = 0, 0, []

    def _room(self, name: str, need: int) -> np.ndarray:
        a = getattr(self, name)
        if need > len(a):
            a = np.concatenate([a, np.zeros(max(need - len(a), len(a) // 2), a.dtype)])
            setattr(self, name, a)
        return a

    def _add(self, chunks: list[str], ids: np.ndarray, lens: np.ndarray) -> None:
        at, n = len(self.index), len(chunks)
        self._room("pool", self.used + len(ids))[self.used : self.used + len(ids)] = ids
        self._room("length", at + n)[at : at + n] = lens
        self._room("start", at + n)[at : at + n] = self.used + np.cumsum(lens) - lens
        self.used += len(ids)
        self.chars += sum(map(len, chunks))
        self.index.update(zip(chunks, range(at, at + n), strict=True))
        if self.decoded:
            t, flat, end = self.encoder.tokens, ids.tolist(), 0
            for k in lens.tolist():
                self.said.append(" ".join([t[i] for i in flat[end : end + k]]))
                end += k

    def _learn(self, chunks: list[str]) -> None:
        words = dict.fromkeys([c for c in chunks if c.isalpha()])
        index, mixed = self.index, []
        for c in chunks:
            if c not in words:
                x = pieces(c)
                if len(x) > 1:
                    mixed.append((c, x))
                words.update(dict.fromkeys([p for p in x if p not in index]))
        words = list(words)
        self._add(words, *self.encoder.many(words))
        if mixed:
            rows = np.array([self.index[p] for _, x in mixed for p in x], np.int64)
            of = np.repeat(np.arange(len(mixed)), [len(x) for _, x in mixed])
            self._add([c for c, _ in mixed], self.gather(rows), np.bincount(of, self.length[rows], len(mixed)).astype(np.int64))

    def rows(self, chunks: list[str]) -> np.ndarray:
        """Row numbers of distinct chunks, learning the unknown ones."""
        index = self.index
        new = [c for c in chunks if c not in index]
        if new:
            if len(index) + len(new) > MAX_CHUNKS or self.chars > MAX_CHARS:
                self._clear()
                index, new = self.index, chunks
            self._learn(new)
        return np.fromiter(map(index.__getitem__, chunks), np.int64, len(chunks))

    def gather(self, rows: np.ndarray) -> np.ndarray:
        lens = self.length[rows].astype(np.int64)
        ends = np.cumsum(lens)
        return self.pool[np.repeat(self.start[rows] - ends + lens, lens) + np.arange(ends[-1] if len(ends) else 0)]

    def batch(self, texts) -> Batch:
        """Texts (an Arrow array or a list; null: empty) encoded."""
        import pyarrow as pa
        import pyarrow.compute as pc

        texts = pc.fill_null(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string()), "")
        strange = pc.match_substring_regex(texts, _ODD)
        odd = np.flatnonzero(np.asarray(strange)).tolist()
        low = pc.utf8_lower(pc.if_else(strange, "", texts) if odd else texts)
        # a stop that ends a word is a chunk of its own, so the word is looked up once with and without it
        low = pc.replace_substring_regex(low, r"([a-z0-9])([,.]) ", r"\1 \2 ")
        cut = pc.utf8_split_whitespace(low)
        coded = cut.flatten().dictionary_encode()
        codes, chunks = np.asarray(coded.indices), coded.dictionary.to_pylist()
        edges = np.asarray(cut.offsets).astype(np.int64) - cut.offsets[0].as_py()
        if "" in chunks:  # what stands before a first and after a last space
            blank = chunks.index("")
            real = codes != blank
            edges = np.concatenate([[0], np.cumsum(real)])[edges]
            codes = codes[real]
            codes = codes - (codes > blank)
            del chunks[blank]
        rows = self.rows(chunks)[codes] if chunks else np.zeros(0, np.int64)
        ids = self.gather(rows)
        ends = np.concatenate([[0], np.cumsum(self.length[rows], dtype=np.int64)])
        lens = ends[edges[1:]] - ends[edges[:-1]]
        if odd:
            parts = np.split(ids, np.cumsum(lens)[:-1])
            for i in odd:
                parts[i] = np.array(self.encoder.text_ids(texts[i].as_py()), np.uint16)
                lens[i] = len(parts[i])
            ids = np.concatenate(parts)
        return Batch(ids, lens, rows, edges, odd)

    def spoken(self, b: Batch):
        """Decoded texts of a batch that this table has just encoded, as an Arrow array."""
        import pyarrow as pa
        import pyarrow.compute as pc

        used, codes = np.unique(b.rows, return_inverse=True)
        words = pa.array([self.said[i] for i in used.tolist()], pa.string())
        text = pc.binary_join(pa.ListArray.from_arrays(pa.array(b.edges, pa.int32()), words.take(pa.array(codes.reshape(-1)))), " ")
        if b.odd:
            said, ends, t = text.to_pylist(), np.cumsum(b.lens), self.encoder.tokens
            for i in b.odd:
                said[i] = " ".join([t[k] for k in b.ids[ends[i] - b.lens[i] : ends[i]].tolist()])
            text = pa.array(said, pa.string())
        return text

    def counts(self, texts) -> np.ndarray:
        """Encoded length of each text (null: empty)."""
        return self.batch(texts).lens

    def ids(self, text: str | None) -> np.ndarray:
        """Ids of one text (null: empty)."""
        return self.batch([text]).ids


def slices(texts, most: int = 4_000_000):
    """(begin, end) of runs of texts (an Arrow array or a list) with about ``most`` bytes or characters, at least one text each."""
    import pyarrow as pa
    import pyarrow.compute as pc

    if isinstance(texts, pa.Array):
        ends = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(texts), 0)), dtype=np.int64)
    else:
        ends = np.cumsum([len(t or "") for t in texts], dtype=np.int64)
    begin = 0
    while begin < len(texts):
        before = ends[begin - 1] if begin else 0
        end = max(begin + 1, int(np.searchsorted(ends, before + most, "right")))
        yield begin, end
        begin = end


_HELD: dict[tuple, ChunkTable] = {}


def let_go() -> None:
    """Drop what this worker holds and give the memory back; workers live on between stages, and each stage has tables of its own."""
    import ctypes

    import pyarrow as pa

    _HELD.clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # other C libraries give it back by themselves
        pass


def table(path: str, kind: str = "library", decoded: bool = False) -> ChunkTable:
    """This worker's table for a vocabulary file; kind 'library' or 'trie'. A worker holds one at a time."""
    key = (path, kind, decoded)
    if key not in _HELD:
        let_go()
        if kind == "trie":
            from mlcurate.llm.trie_bpe import TrieEncoder

            _HELD[key] = ChunkTable(TrieEncoder(path), decoded)
        else:
            _HELD[key] = ChunkTable(LibraryEncoder(path), decoded)
    return _HELD[key]


def vocabulary(path: str) -> dict:
    with open(path, encoding="utf-8") as f:
        return json.load(f)
