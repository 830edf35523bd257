"""Whole texts to token ids with the tokenizers library, by way of a bounded table of words already seen."""

from __future__ import annotations

import os
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import IdTable, spread

#: Bytes of a worker's table of words; beyond it the table starts anew.
TABLE_BYTES = 192 << 20
#: Words looked up at once.
WORDS = 1 << 18
#: Words that split for certain into their letters and their marks, whatever stands around them.
_PLAIN = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]+)([.,!?;:]*)")


class WordEncoder:
    """Ids of texts under the vocabulary file's lower-casing word tokenizer.

    The tokenizer never joins what white space separates, and it ends every letter run with an end-of-word token.
    So a text's ids are its words' ids in a row, and many plain words can be encoded in one call and cut apart again.
    """

    def __init__(self, path: str, literal: bool = False):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.encode_special_tokens = literal  # strings of special tokens are then ordinary text
        vocab = self.tok.get_vocab(with_added_tokens=True)
        self.size = max(vocab.values()) + 1
        self.ends = np.zeros(self.size, bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        self.marks = {s: self.tok.encode(s, add_special_tokens=False).ids for s in [""]}
        self.table = IdTable(TABLE_BYTES)

    def _ids(self, text: str) -> list[int]:
        return self.tok.encode(text, add_special_tokens=False).ids

    def _learn(self, words: list[str]) -> None:
        match = _PLAIN.fullmatch
        plain, cores, marks, odd = [], [], [], []
        for w in words:
            if m := match(w):
                plain.append(w)
                cores.append(m[1].lower())
                marks.append(m[2])
            else:
                odd.append(w)
        # letter runs have entries of their own, under a name that no word can have
        fresh = [c for c in dict.fromkeys(cores) if c + " " not in self.table.where]
        for lo in range(0, len(fresh), 4096):
            part = fresh[lo : lo + 4096]
            ids = np.array(self._ids(" ".join(part)), np.uint32)
            stops = np.flatnonzero(self.ends[ids]) + 1
            if len(stops) != len(part):
                raise ValueError("a letter run did not end in one end-of-word token")
            self.table.store([c + " " for c in part], ids, np.diff(np.concatenate(([0], stops))))
        if plain:
            core, lengths = self.table.gather(np.fromiter((self.table.where[c + " "] for c in cores), np.int64, len(cores)))
            for m in set(marks) - set(self.marks):
                self.marks[m] = self._ids(m)
            tails = [self.marks[m] for m in marks]
            n_tail = np.fromiter(map(len, tails), np.int64, len(tails))
            total = lengths + n_tail
            out = np.empty(int(total.sum()), np.uint32)
            tail = np.ones(len(out), bool)
            tail[spread(np.cumsum(total) - total, lengths)] = False
            out[~tail] = core
            out[tail] = np.fromiter((i for t in tails for i in t), np.uint32, int(n_tail.sum()))
            self.table.store(plain, out, total)
        if odd:
            found = [self._ids(w) for w in odd]
            n = np.fromiter(map(len, found), np.int64, len(found))
            self.table.store(odd, np.fromiter((i for f in found for i in f), np.uint32, int(n.sum())), n)

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids one after another, and the number of ids of each text; null counts as empty."""
        words = pc.ascii_split_whitespace(pc.fill_null(texts, ""))
        n_words = pc.list_value_length(words).to_numpy(zero_copy_only=False).astype(np.int64)
        flat, parts, lengths = words.flatten(), [], []
        for lo in range(0, len(flat), WORDS):
            coded = pc.dictionary_encode(flat.slice(lo, WORDS))
            distinct = coded.dictionary.to_pylist()
            if self.table.full:
                self.table.clear()
            where = self.table.where
            fresh = [w for w in distinct if w not in where]
            if fresh:
                self._learn(fresh)
            slots = np.fromiter((where[w] for w in distinct), np.int64, len(distinct))
            ids, n = self.table.gather(slots[coded.indices.to_numpy()])
            parts.append(ids), lengths.append(n)
        if not parts:
            return np.zeros(0, np.uint32), np.zeros(len(texts), np.int64)
        total = np.concatenate(([0], np.cumsum(np.concatenate(lengths))))
        edge = np.concatenate(([0], np.cumsum(n_words)))
        return np.concatenate(parts), np.diff(total[edge])


_MADE: dict[tuple[str, bool], WordEncoder] = {}


def encoder(path: str, literal: bool = False) -> WordEncoder:
    """One encoder a Python worker, kept between its tasks."""
    if (path, literal) not in _MADE:
        _MADE[path, literal] = WordEncoder(path, literal)
    return _MADE[path, literal]


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
