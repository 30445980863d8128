"""Token identifiers of a public word-end BPE vocabulary, exactly as the tokenizers library gives them, in bulk.

White space separates words for this tokenizer, and a word's identifiers depend on nothing around it. So each batch
encodes its distinct words once. Words of plain Latin letters are merged together in numpy, by the vocabulary's own
merge ranks; every other word goes through the library itself. Tests hold the outcome against the library's on whole
texts.
"""

from __future__ import annotations

import json
import os
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

LETTERS = "A-Za-zÀ-ÖØ-öø-ÿ"
TRAILING = ".,!?;:|*#$%&)("
PLAIN_WORD = f"^[{LETTERS}]+[{TRAILING}]*$"
LONGEST_PLAIN = 40
NONE = np.int32(2**31 - 1)


def vocabulary_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class WordEncoder:
    """Identifiers of distinct words."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        vocab, merges = model["vocab"], [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        self.size = max(vocab.values()) + 1
        letters = _byte_letters()
        self.inner = np.array([vocab.get(c, -1) for c in letters], np.int32)
        self.final = np.array([vocab.get(c + "</w>", -1) for c in letters], np.int32)
        keys = np.array([vocab[a] * self.size + vocab[b] for a, b in merges], np.int64)
        self._table(keys, np.array([vocab[a + b] for a, b in merges], np.int32))

    def _table(self, keys: np.ndarray, made: np.ndarray) -> None:
        """Pair of identifiers -> merge rank, by two hash tables and a search among the few keys that neither holds."""
        self.made = np.append(made, np.int32(0))
        n = 1 << 19
        self.slots, rest = [], np.arange(len(keys))
        for factor in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F):
            at = self._slot(keys[rest], factor, n)
            key, rank = np.full(n, -1, np.int64), np.full(n, NONE, np.int32)
            key[at[::-1]], rank[at[::-1]] = keys[rest][::-1], rest[::-1].astype(np.int32)
            self.slots.append((factor, key, rank))
            rest = rest[key[at] != keys[rest]]
        order = np.argsort(keys[rest])
        self.rest_keys, self.rest_ranks = keys[rest][order], rest[order].astype(np.int32)

    @staticmethod
    def _slot(key: np.ndarray, factor: int, n: int) -> np.ndarray:
        return ((key.view(np.uint64) * np.uint64(factor)) >> np.uint64(64 - n.bit_length() + 1)).astype(np.int64)

    def rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        key = a.astype(np.int64) * self.size + b
        out = np.full(len(key), NONE, np.int32)
        for factor, keys, ranks in self.slots:
            at = self._slot(key, factor, len(keys))
            hit = keys[at] == key
            out[hit] = ranks[at[hit]]
        if len(self.rest_keys):
            at = np.minimum(np.searchsorted(self.rest_keys, key), len(self.rest_keys) - 1)
            hit = self.rest_keys[at] == key
            out[hit] = self.rest_ranks[at[hit]]
        return out

    def _merge(self, raw: np.ndarray, start: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Words of n bytes each: their identifiers, padded, and how many each has."""
        ids = self.inner[raw[start[:, None] + np.arange(n)]]
        ids[:, -1] = self.final[raw[start + n - 1]]
        count = np.full(len(ids), n)
        if n == 1:
            return ids, count
        ranks = self.rank(ids[:, :-1].ravel(), ids[:, 1:].ravel()).reshape(len(ids), n - 1)
        live, cur, rk, column = np.arange(len(ids)), ids.copy(), ranks, np.arange(n)
        while len(live):
            at = rk.argmin(axis=1)
            row = np.arange(len(live))
            best = rk[row, at]
            go = best != NONE
            if not go.all():
                ids[live[~go], : cur.shape[1]] = cur[~go]
                live, cur, rk, at, best = live[go], cur[go], rk[go], at[go], best[go]
                row = np.arange(len(live))
                if not len(live):
                    break
            cur[row, at] = self.made[best]
            width = cur.shape[1] - 1
            after = column[:width] > at[:, None]
            cur = np.where(after, cur[:, 1:], cur[:, :-1])
            count[live] -= 1
            if width == 1:
                ids[live, :1] = cur
                break
            rk = np.where(after[:, : width - 1] | (column[: width - 1] == at[:, None]), rk[:, 1:], rk[:, :-1])
            for side in (-1, 0):
                left = at + side
                ok = (left >= 0) & (left < count[live] - 1)
                r, c = row[ok], left[ok]
                rk[r, c] = self.rank(cur[r, c], cur[r, c + 1])
                past = (left >= 0) & (left == count[live] - 1) & (left < width - 1)
                rk[row[past], left[past]] = NONE
        return ids, count

    def distinct(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(identifiers of all words in turn, n + 1 bounds) of distinct words."""
        total = len(words)
        plain = pc.match_substring_regex(words, PLAIN_WORD).to_numpy(zero_copy_only=False) & (pc.binary_length(words).to_numpy() <= LONGEST_PLAIN)
        core = pc.utf8_lower(pc.utf8_rtrim(words, characters=TRAILING))
        core_bytes = pc.binary_length(core).to_numpy()
        bounds = np.frombuffer(core.buffers()[1], np.int32)[core.offset : core.offset + total + 1].astype(np.int64)
        raw = np.frombuffer(core.buffers()[2] or b"", np.uint8)
        parts: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []  # word, first, count, identifiers
        for n in np.unique(core_bytes[plain]):
            which = np.flatnonzero(plain & (core_bytes == n))
            ids, count = self._merge(raw, bounds[which], int(n))
            keep = np.arange(ids.shape[1]) < count[:, None]
            parts.append((which, np.zeros(len(which), np.int64), count, ids[keep]))
        tails = np.flatnonzero(plain & (pc.binary_length(words).to_numpy() > core_bytes))
        if len(tails):  # what follows the letters is a token sequence of its own
            ends = pc.utf8_slice_codeunits(words.take(pa.array(tails)), start=-LONGEST_PLAIN)
            ends = pc.replace_substring_regex(ends, f"^.*[{LETTERS}]", "")
            coded = pc.dictionary_encode(ends)
            sets = self._by_library(coded.dictionary.to_pylist())
            self._tail(parts, tails, coded.indices.to_numpy(), sets)
        odd = np.flatnonzero(~plain)
        if len(odd):
            sets = self._by_library(words.take(pa.array(odd)).to_pylist())
            self._tail(parts, odd, np.arange(len(odd)), sets)
        if not parts:
            return np.empty(0, np.uint32), np.zeros(total + 1, np.int64)
        word = np.concatenate([np.repeat(p[0], p[2]) for p in parts])
        flat = np.concatenate([p[3] for p in parts])
        order = np.argsort(word, kind="stable")  # parts of a word are in order of parts
        counts = np.bincount(word, minlength=total)
        return flat[order].astype(np.uint32), np.concatenate([[0], np.cumsum(counts)])

    def _by_library(self, words: list[str]) -> list[list[int]]:
        return [x.ids for x in self.library.encode_batch_fast(words, add_special_tokens=False)]

    @staticmethod
    def _tail(parts: list, which: np.ndarray, index: np.ndarray, sets: list[list[int]]) -> None:
        sizes = np.array([len(s) for s in sets], np.int64)
        flat = np.array([i for s in sets for i in s], np.int64)
        first = np.concatenate([[0], np.cumsum(sizes)])[:-1]
        count = sizes[index]
        parts.append((which, np.zeros(len(which), np.int64), count, flat[spread(first[index], count)]))


def spread(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """first, first + 1, ... count numbers for each pair, joined."""
    total = int(count.sum())
    shift = np.repeat(first - np.concatenate([[0], np.cumsum(count)[:-1]]), count)
    return np.arange(total) + shift


def _byte_letters() -> list[str]:
    """The printable character that byte-level vocabularies use for each byte."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out, extra = [""] * 256, 0
    for b in range(256):
        if b in shown:
            out[b] = chr(b)
        else:
            out[b] = chr(256 + extra)
            extra += 1
    return out


@lru_cache(maxsize=1)
def encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


def encode(texts: pa.Array, path: str, end_id: int | None) -> tuple[np.ndarray, np.ndarray]:
    """(identifiers of all texts in turn, n + 1 bounds); a null text is empty."""
    texts = pc.fill_null(texts, "")
    lists = pc.ascii_split_whitespace(texts)
    per_doc = pc.list_value_length(lists).to_numpy()
    coded = pc.dictionary_encode(lists.flatten())
    words = coded.dictionary
    ids, bounds = encoder(path).distinct(words)
    index = coded.indices.to_numpy()
    if end_id is not None:
        ids, bounds = np.append(ids, np.uint32(end_id)), np.append(bounds, bounds[-1] + 1)
        index = np.insert(index, np.cumsum(per_doc), len(words))
        per_doc = per_doc + 1
    count = np.diff(bounds)[index]
    out = ids[spread(bounds[:-1][index], count)]
    total = np.concatenate([[0], np.cumsum(count)])
    return out, total[np.concatenate([[0], np.cumsum(per_doc)])]
