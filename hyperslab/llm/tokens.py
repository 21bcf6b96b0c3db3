"""Token ids of many texts at once, by files of the tokenizers library.

A text is cut at places where no token of the given kind of file can reach across, each different piece
is encoded once, and the ids are put together by position. Pieces of plain Latin characters are cut into
words by the file's own pattern and go straight to its merge model; all others go through the whole
tokenizer. Tests hold this against encoding whole texts.
"""

from __future__ import annotations

from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

#: A byte-level file joins a space to the word after it. Runs that end in two spaces, or white space and a last space, bind differently.
_BOUND = "  |[\\s\\v\\x{85}\\pZ] $"
#: Pieces and words whose ids a process keeps.
_KEPT = 400_000

# The word patterns of the two kinds of file.
_BYTE_LEVEL_WORDS = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
_WORD_END_WORDS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: Characters that no normalisation form or pattern version treats differently.
_PLAIN = regex.compile(r"[\n\x20-\x7e\xa1-\xac\xae-\xff]*")


def _byte_letters() -> dict[int, str]:
    """The letters by which byte-level files write bytes: printable ones as themselves, the rest from U+0100 on."""
    printable = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    others = (b for b in range(256) if b not in printable)
    return {b: chr(b) for b in printable} | {b: chr(256 + k) for k, b in enumerate(others)}


@lru_cache
def encoder(path: str, word_ends: bool) -> Encoder:
    """The process's encoder of that file, with the pieces it knows."""
    return Encoder(path, word_ends)


class Encoder:
    """ids of texts, without special tokens. word_ends: the file drops white space (else it is byte-level)."""

    def __init__(self, path: str, word_ends: bool):
        from tokenizers import Tokenizer

        self.tokenizer, self.word_ends = Tokenizer.from_file(path), word_ends
        self.model = self.tokenizer.model
        self.words = regex.compile(_WORD_END_WORDS if word_ends else _BYTE_LEVEL_WORDS)
        self.letters = _byte_letters()
        self.known: dict[str, bytes] = {}
        self.known_words: dict[str, bytes] = {}

    def _word(self, word: str) -> bytes:
        ids = self.known_words.get(word)
        if ids is None:
            spelt = word.translate(self.letters) if word.isascii() else word.encode().decode("latin-1").translate(self.letters)
            ids = self.known_words[word] = array("I", [t.id for t in self.model.tokenize(spelt)]).tobytes()
        return ids

    def _ids(self, pieces: list[str]) -> list[bytes]:
        known, plain, words, word = self.known, _PLAIN.fullmatch, self.words.findall, self._word
        if len(known) > _KEPT or len(self.known_words) > _KEPT:
            known.clear()
            self.known_words.clear()
        odd = []
        for p in pieces:
            if p not in known:
                if plain(p) and "<|" not in p:
                    known[p] = b"".join([word(w) for w in words(p.lower() if self.word_ends else p)])
                else:
                    odd.append(p)
        for at in range(0, len(odd), 1024):
            some = odd[at : at + 1024]
            for p, e in zip(some, self.tokenizer.encode_batch_fast(some, add_special_tokens=False), strict=True):
                known[p] = np.array(e.ids, np.uint32).tobytes()
        return [known[p] for p in pieces]

    def __call__(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids, offsets of the texts among them); a null text is empty."""
        if texts.offset:  # string kernels misread slices
            texts = texts.take(pa.array(np.arange(len(texts))))
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        if self.word_ends:
            split = pc.ascii_split_whitespace(texts)
            flat, ends = split.flatten(), split.offsets.to_numpy() - split.offsets[0].as_py()
        else:
            whole = pc.match_substring_regex(texts, _BOUND).to_numpy(zero_copy_only=False)
            split = pc.split_pattern(texts, " ")
            flat, ends = split.flatten(), split.offsets.to_numpy() - split.offsets[0].as_py()
            first = np.zeros(len(flat), bool)
            first[ends[:-1]] = True  # a split text has one piece at least
            space, none = pa.scalar(" ", pa.large_string()), pa.scalar("", pa.large_string())
            flat = pc.binary_join_element_wise(pc.if_else(pa.array(first), none, space), flat, none)
            if whole.any():
                keep = ~np.repeat(whole, np.diff(ends))
                keep[ends[:-1][whole]] = True
                flat = pc.replace_with_mask(flat, pa.array(np.isin(np.arange(len(flat)), ends[:-1][whole])), texts.filter(pa.array(whole)))
                flat, ends = flat.filter(pa.array(keep)), np.concatenate(([0], np.cumsum(keep)))[ends]
        coded = flat.dictionary_encode()
        of = self._ids(coded.dictionary.to_pylist())
        codes = coded.indices.to_numpy(zero_copy_only=False)
        sizes = np.fromiter(map(len, of), np.int64, len(of)) // 4
        starts, n = np.concatenate(([0], np.cumsum(sizes)))[:-1], sizes[codes]
        at = np.concatenate(([0], np.cumsum(n)))
        where = np.repeat(starts[codes] - at[:-1], n) + np.arange(at[-1])
        return np.frombuffer(b"".join(of), np.uint32).take(where), at[ends]
