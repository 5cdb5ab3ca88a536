"""BPE by prefix-sharing trie traversal.

Distinct words, sorted, are the leaves of a trie that is walked depth first: a
path's state holds, for each of its nodes, the last token of the encoding of the
text down to that node. Going from one word to the next keeps the nodes that both
share, so a shared prefix is encoded once. The last token of a node is the longest
vocabulary token ending there that may follow the last token of the node where it
starts; two tokens may follow each other if merging their joint symbols gives
exactly those two tokens back, which is looked up in a cache of pairs. The first
symbol of a word and its last (which carries the word-end mark) are nodes like any other.
"""

from __future__ import annotations

import re

import numpy as np

from mlcurate.llm.tokens import vocabulary

#: Pairs held in the cache (bounds a worker's memory).
_MAX_PAIRS = 500_000


def _byte_symbols() -> list[str]:
    """Symbol of each byte in byte-level vocabularies: printable Latin-1 bytes stand for themselves, the rest follow from U+0100 on."""
    kept = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out, nxt = [""] * 256, 0x100
    for b in kept:
        out[b] = chr(b)
    for b in range(256):
        if not out[b]:
            out[b] = chr(nxt)
            nxt += 1
    return out


class TrieEncoder:
    def __init__(self, path: str):
        spec = vocabulary(path)
        model = spec["model"]
        self.suffix = model["end_of_word_suffix"] or ""
        self.vocab: dict[str, int] = model["vocab"]
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        self.rank = {(self.vocab[a], self.vocab[b]): (i, self.vocab[a + b]) for i, (a, b) in enumerate(pairs)}
        self.tokens = [""] * (1 + max([*self.vocab.values(), *(t["id"] for t in spec["added_tokens"])]))
        for t, i in self.vocab.items():
            self.tokens[i] = t
        for t in spec["added_tokens"]:
            self.tokens[t["id"]] = t["content"]
        self.bytes = _byte_symbols()
        self.longest = max(len(self._split(t)) for t in self.vocab)
        self.path = path
        self._lib = None
        self.specials = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special = re.compile("(" + "|".join(map(re.escape, self.specials)) + ")")
        self.size = [len(self._split(t)) if t else 0 for t in self.tokens]
        self.fits_cache: dict[int, bool] = {}
        self.whole: dict[str, bool] = {}

    def _split(self, token: str) -> list[str]:
        s = self.suffix
        if s and token.endswith(s) and len(token) > len(s):
            token = token[: -len(s)]
            return [*token[:-1], token[-1] + s]
        return list(token)

    def _merge(self, symbols: list[int]) -> list[int]:
        """Plain merging by rank; only for pairs of tokens and single tokens, so inputs are short."""
        rank = self.rank
        while len(symbols) > 1:
            best = min(((rank.get(p, (1 << 60, -1)), i) for i, p in enumerate(zip(symbols, symbols[1:], strict=False))), default=None)
            if best is None or best[0][1] < 0:
                break
            (_, new), _ = best
            first = best[1]
            pair = (symbols[first], symbols[first + 1])
            out, i = [], 0
            while i < len(symbols):
                if i + 1 < len(symbols) and (symbols[i], symbols[i + 1]) == pair:
                    out.append(new)
                    i += 2
                else:
                    out.append(symbols[i])
                    i += 1
            symbols = out
        return symbols

    def _symbols(self, token: int) -> list[int]:
        return [self.vocab[x] for x in self._split(self.tokens[token])]

    def _real(self, token: str) -> bool:
        """Does this token come out of merging its own symbols?"""
        if (got := self.whole.get(token)) is None:
            i = self.vocab[token]
            got = self.whole[token] = self._merge(self._symbols(i)) == [i]
        return got

    def _fits(self, a: int, b: int) -> bool:
        key = (a << 20) | b
        if (got := self.fits_cache.get(key)) is None:
            if len(self.fits_cache) > _MAX_PAIRS:
                self.fits_cache.clear()
            got = self.fits_cache[key] = self._merge(self._symbols(a) + self._symbols(b)) == [a, b]
        return got

    def _state(self, last: list[int], text: str, end: int, mark: str) -> int:
        """Last token at depth ``end`` of a path: the longest token ending there that fits what stands before it."""
        vocab, longest = self.vocab, self.longest
        for begin in range(max(0, end - longest), end):
            token = text[begin:end] + mark
            i = vocab.get(token)
            if i is not None and (end - begin == 1 or self._real(token)) and (begin == 0 or self._fits(last[begin - 1], i)):
                return i
        raise ValueError(f"no encoding for {text!r}")

    def many(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words, one after the other, and how many each has."""
        table = self.bytes
        return self.walk([w if w.isascii() and w.isprintable() else "".join([table[b] for b in w.encode()]) for w in words])

    def walk(self, spelt: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The traversal, over words spelt in byte symbols."""
        suffix, size = self.suffix, self.size
        out: list[list[int]] = [[]] * len(spelt)
        last: list[int] = []  # last tokens of the nodes of the current path
        before = ""
        for k in sorted(range(len(spelt)), key=spelt.__getitem__):
            text = spelt[k]
            n = len(text)
            if not n:
                continue
            keep, most = 0, min(len(before), n - 1, len(last))
            while keep < most and before[keep] == text[keep]:
                keep += 1
            del last[keep:]
            for end in range(keep + 1, n):
                last.append(self._state(last, text, end, ""))
            token = self._state(last, text, n, suffix)
            ids, at = [token], n - size[token]
            while at > 0:
                token = last[at - 1]
                ids.append(token)
                at -= size[token]
            ids.reverse()
            out[k] = ids
            before = text[: n - 1]
        return np.array([i for x in out for i in x], np.uint16), np.array([len(x) for x in out], np.int64)

    def text_ids(self, text: str) -> list[int]:
        """Texts with characters beyond the cached range: normalised and cut by the library, encoded by the trie."""
        if self._lib is None:
            from tokenizers import Tokenizer

            self._lib = Tokenizer.from_file(self.path)
        ids: list[int] = []
        for part in self.special.split(text):
            if part in self.specials:
                ids.append(self.specials[part])
            elif part:
                cut = self._lib.pre_tokenizer.pre_tokenize_str(self._lib.normalizer.normalize_str(part))
                ids += self.walk([w for w, _ in cut])[0].tolist()
        return ids
