"""Token ids and counts of whole texts by a public BPE vocabulary, one pre-token at a time.

A BPE never merges across pre-tokens, so ids and counts can be kept by pre-token. Texts of plain
characters (ASCII, Latin-1 letters) are cut here by an equal expression of the standard library's
re; every other text, and one with a special string inside, is cut by the tokenizers library's own
normaliser and pre-tokenizer. The ids of a pre-token always come from that library's model.
"""

from __future__ import annotations

import contextlib
import ctypes
import os
import re
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from tokenizers import Tokenizer
from tokenizers.pre_tokenizers import WhitespaceSplit

#: Characters whose class is the same for every regular expression engine.
_ODD = re.compile("[^\t\n\r -~À-ÖØ-öø-ÿ]")
# The pre-token patterns of the two vocabularies, for plain characters.
_BYTE_LEVEL = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[A-Za-zÀ-ÖØ-öø-ÿ]+| ?[0-9]+| ?[^\sA-Za-zÀ-ÖØ-öø-ÿ0-9]+|\s+(?!\S)|\s+")
_WORD_LEVEL = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^\sa-zß-öø-ÿ0-9]+")
#: What the fast cuts leave out: an odd character, a special string, a space before white space or at the end.
_SLOW = "[^\t\n\r -~À-ÖØ-öø-ÿ]|<\\||[ ][ \t\n\r]|[ ]$"

#: Two bytes that UTF-8 never has: one parts pre-tokens, one marks them.
_PART, _MARK = b"\xfe", b"\xff"


def _byte_characters() -> dict[int, str]:
    """The printable stand-in of each byte: itself where printable in Latin-1, else from 256 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(hidden)}


class _Kept:
    """Ids of texts within a bound of entries, as flat arrays of a few bytes an entry. When the bound
    is reached, what the last call used stays, so frequent texts do."""

    def __init__(self, most: int, dtype: np.dtype) -> None:
        self.most, self.texts = most, pa.array([], pa.string())
        self.ids, self.sizes = np.empty(0, dtype), np.empty(0, np.int32)

    def get(self, texts: pa.Array, make: Callable[[pa.Array], tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of distinct texts: a flat array, and where in it each text's ids start and how many
        they are. make gives the ids of texts that are not kept, in a row, and their numbers."""
        at = pc.index_in(texts, value_set=self.texts)
        lacking = at.is_null()
        own = texts.filter(lacking)
        ids, sizes = make(own)
        place = pc.fill_null(at, 0).to_numpy().astype(np.int64)
        place[lacking.to_numpy(zero_copy_only=False)] = len(self.texts) + np.arange(len(own))
        ids, sizes = np.concatenate((self.ids, ids)), np.concatenate((self.sizes, sizes.astype(np.int32)))
        starts = np.cumsum(sizes, dtype=np.int64) - sizes
        if len(sizes) <= self.most:
            self.texts, self.ids, self.sizes = pa.concat_arrays([self.texts, own]), ids, sizes
        else:
            last = place[: self.most]
            self.texts = texts.slice(0, len(last))
            self.ids, _ = _gathered(ids, starts[last], sizes[last])
            self.sizes = sizes[last]
        return ids, starts[place], sizes[place]


class PreTokenizer:
    """Pre-tokens, ids and counts of texts by the vocabulary file at path.

    most bounds the texts whose ids are kept from slice to slice: units, which stand between spaces,
    and pre-tokens, half of it each.
    """

    def __init__(self, path: str, most: int = 1_000_000) -> None:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a worker has one core
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.model = self.library.model
        self.words = self.library.normalizer is not None  # lower-cased, white space dropped
        special = {t.content: i for i, t in self.library.get_added_tokens_decoder().items()}
        self.special = special
        self._special = re.compile("(" + "|".join(map(re.escape, special)) + ")") if special else None
        self._byte = _byte_characters()
        self._most = most
        wide = self.library.get_vocab_size(with_added_tokens=True) > 65536
        self.dtype = np.dtype("<u4") if wide else np.dtype("<u2")
        # The model alone, for pre-tokens whose bytes are shown already.
        self._merges = Tokenizer(self.model)
        self._merges.pre_tokenizer = WhitespaceSplit()
        self._shown = np.array([ord(self._byte[i]) for i in range(256)], "<u2")
        self._shown[_PART[0]] = 32
        # A mark before a pre-token is a piece of its own if nothing is ever merged with it.
        mark, held = self._byte[_MARK[0]], self.library.get_vocab(with_added_tokens=False)
        alone = {t for t in held if mark in t} <= {mark, mark + (self.model.end_of_word_suffix or "")}
        simple = self.model.dropout is None and not self.model.ignore_merges and not self.model.continuing_subword_prefix
        self._mark = held.get(mark) if alone and simple else None
        self._kept_units, self._kept_pre_tokens = _Kept(most // 2, self.dtype), _Kept(most // 2, self.dtype)

    def pieces(self, pre_token: str) -> list[int]:
        shown = pre_token.encode().decode("latin-1").translate(self._byte)
        return [t.id for t in self.model.tokenize(shown)]

    def _made(self, pre_tokens: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of distinct pre-tokens, in a row, and how many each has: the library's model gets them
        some at a time, parted by spaces, which no pre-token has once its bytes are shown."""
        ids, sizes = [np.empty(0, self.dtype)], [np.empty(0, np.int64)]
        for i in range(0, len(pre_tokens), 4096):
            own = pre_tokens.slice(i, 4096)
            parted = pc.binary_join_element_wise(_PART if self._mark is None else _PART + _MARK, own.cast(pa.binary()), b"")
            shown = self._shown[_flat(parted)].tobytes().decode("utf-16-le")
            if self._mark is None:
                found = self._merges.encode(shown, add_special_tokens=False)
                ids.append(np.array(found.ids, self.dtype))
                sizes.append(np.bincount(np.array(found.word_ids, np.int64), minlength=len(own)))
            else:  # the faster call does not tell the words, so a mark begins each
                (found,) = self._merges.encode_batch_fast([shown], add_special_tokens=False)
                marked = np.array(found.ids, self.dtype)
                starts = np.flatnonzero(marked == self._mark)
                ids.append(np.delete(marked, starts))
                sizes.append(np.diff(starts, append=len(marked)) - 1)
        return np.concatenate(ids), np.concatenate(sizes)

    def counts(self, pre_tokens: pa.Array) -> np.ndarray:
        """How many pieces each distinct pre-token has."""
        sizes = self._made(pre_tokens)[1]
        if self.special:
            sizes[pc.is_in(pre_tokens, value_set=pa.array(list(self.special), pa.string())).to_numpy(zero_copy_only=False)] = 1
        return sizes

    def _cut(self, units: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
        """The distinct pre-tokens of units, the number of each in its place, and how many a unit has."""
        cut = (_WORD_LEVEL if self.words else _BYTE_LEVEL).findall
        # The units up to the first without a space before a character are cut as one text: each of their
        # spaces begins a pre-token there, as it does in the unit alone.
        spaced = pc.match_substring_regex(units, r"^ \S").to_numpy(zero_copy_only=False)
        n = 0 if self.words else int(np.argmin(np.append(spaced, False)))
        joined = cut(_flat(units.slice(0, n)).tobytes().decode())
        lists = list(map(cut, units.slice(n).to_pylist()))
        coded = pa.array(joined + [p for own in lists for p in own], pa.string()).dictionary_encode()
        codes = coded.indices.to_numpy()
        starts = np.flatnonzero(pc.starts_with(coded.dictionary, " ").to_numpy(zero_copy_only=False)[codes[: len(joined)]])
        many = np.concatenate((np.diff(starts, append=len(joined)), np.fromiter(map(len, lists), np.int64, len(lists))))
        return coded.dictionary, codes, many.astype(np.int32)

    def _units_made(self, units: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        pre_tokens, codes, many = self._cut(units)
        ids, starts, sizes = self._kept_pre_tokens.get(pre_tokens, self._made)
        flat, ends = _gathered(ids, starts[codes], sizes[codes])
        ends = np.concatenate(([0], ends))[np.concatenate(([0], np.cumsum(many)))]
        return flat, np.diff(ends)

    def _odd(self, text: str) -> bool:
        return _ODD.search(text) is not None or ("<|" in text and self._special is not None)

    def _by_library(self, text: str) -> list[str]:
        """Pre-tokens as the library cuts them; special strings are pre-tokens of their own."""
        found: list[str] = []
        for i, part in enumerate(self._special.split(text) if self._special else [text]):
            if i % 2:
                found.append(part)
            elif part:
                if self.library.normalizer is not None:
                    part = self.library.normalizer.normalize_str(part)
                found.extend(part[a:b] for _, (a, b) in self.library.pre_tokenizer.pre_tokenize_str(part))
        return found

    def pre_tokens(self, text: str) -> list[str]:
        if self._odd(text):
            return self._by_library(text)
        return _WORD_LEVEL.findall(text.lower()) if self.words else _BYTE_LEVEL.findall(text)

    def ids(self, text: str) -> np.ndarray:
        """The ids of one whole text."""
        lists = [[self.special[p]] if p in self.special else self.pieces(p) for p in self.pre_tokens(text)]
        return np.array([i for own in lists for i in own], self.dtype)

    def _units(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, pa.Array]:
        """Cut plain texts where BPE never merges, at white space: the number of each unit, where
        each text starts, and the distinct units."""
        lists = pc.ascii_split_whitespace(pc.utf8_lower(texts)) if self.words else pc.split_pattern(texts, " ")
        offsets = lists.offsets.to_numpy().astype(np.int64)
        values = lists.values.slice(offsets[0], offsets[-1] - offsets[0])
        offsets = offsets - offsets[0]
        if self.words:
            coded = values.dictionary_encode()
            return coded.indices.to_numpy(), offsets, coded.dictionary
        # A space belongs to the pre-token after it; the first unit of a text has none before it.
        later = np.ones(len(values), bool)
        later[offsets[:-1]] = False
        coded, starts = values.filter(pa.array(later)).dictionary_encode(), pc.list_element(lists, 0).dictionary_encode()
        codes = np.empty(len(values), np.int32)
        codes[later] = coded.indices.to_numpy()
        codes[~later] = starts.indices.to_numpy() + len(coded.dictionary)
        return codes, offsets, pa.concat_arrays([pc.binary_join_element_wise("", coded.dictionary, " "), starts.dictionary])

    def ids_of(self, texts: pa.Array) -> list[np.ndarray]:
        """The ids of each whole text; a null text has none."""
        texts = pc.fill_null(texts.cast(pa.string()), "")
        slow = pc.match_substring_regex(texts, _SLOW).to_numpy(zero_copy_only=False)
        found: list[np.ndarray] = [None] * len(texts)
        for i in np.flatnonzero(slow):
            found[i] = self.ids(texts[int(i)].as_py())
        if not slow.all():
            codes, offsets, units = self._units(texts.filter(pa.array(~slow)))
            ids, starts, sizes = self._kept_units.get(units, self._units_made)
            own, first = np.flatnonzero(~slow), 0
            while first < len(own):  # some texts at a time, as the steps in between take much room
                last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + 200_000, "right")) - 1)
                some = codes[offsets[first] : offsets[last]]
                flat, ends = _gathered(ids, starts[some], sizes[some])
                bounds = np.concatenate(([0], ends))[offsets[first : last + 1] - offsets[first]]
                for i, a, b in zip(own[first:last].tolist(), bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
                    found[i] = flat[a:b]
                first = last
        return found

    def frequencies(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, list[str]]:
        """Each pre-token of each text: the text's number, the pre-token's number, and the distinct
        pre-tokens. The pairs repeat as the pre-tokens do."""
        texts = pc.fill_null(texts.cast(pa.string()), "")
        slow = pc.match_substring_regex(texts, _SLOW).to_numpy(zero_copy_only=False)
        names: list[str] = []
        docs, found = [], []
        if not slow.all():
            codes, offsets, units = self._units(texts.filter(pa.array(~slow)))
            pre_tokens, kept, many = self._cut(units)
            flat, ends = _gathered(kept, (np.cumsum(many, dtype=np.int64) - many)[codes], many[codes])
            bounds = np.concatenate(([0], ends))[offsets]
            docs.append(np.repeat(np.flatnonzero(~slow), np.diff(bounds)))
            found.append(flat.astype(np.int64))
            names = pre_tokens.to_pylist()
        if slow.any():
            number = {p: n for n, p in enumerate(names)}
            for i in np.flatnonzero(slow):
                own = [number.setdefault(p, len(number)) for p in self.pre_tokens(texts[int(i)].as_py())]
                docs.append(np.full(len(own), i, np.int64))
                found.append(np.array(own, np.int64))
            names = list(number)
        empty = np.empty(0, np.int64)
        return np.concatenate([*docs, empty]), np.concatenate([*found, empty]), names


def _flat(values: pa.Array) -> np.ndarray:
    """The bytes of strings without nulls, one after the other."""
    data = values.buffers()[2]
    if not len(values) or data is None:
        return np.empty(0, np.uint8)
    ends = np.frombuffer(values.buffers()[1], np.int32)
    return np.frombuffer(data, np.uint8)[ends[values.offset] : ends[values.offset + len(values)]]


def _gathered(kept: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The runs of kept that begin at starts, one after the other, and where each then ends."""
    ends = np.cumsum(sizes, dtype=np.int64)
    at = np.repeat((starts - (ends - sizes)).astype(np.int32), sizes)
    at += np.arange(len(at), dtype=np.int32)
    return kept[at], ends


def by_bytes(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = 12_000_000) -> Iterator[pa.RecordBatch]:
    """Slices of the batches with at most so many bytes of text each, or one row. At the end freed
    memory goes back to the system, as a worker lives on for other tasks."""
    for batch in batches:
        size = np.concatenate(([0], np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy())))
        i = 0
        while i < batch.num_rows:
            j = max(i + 1, int(np.searchsorted(size, size[i] + most, "right")) - 1)
            yield batch.slice(i, j - i)
            i = j
    del batches
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not every C library has it
        ctypes.CDLL(None).malloc_trim(0)


@lru_cache(maxsize=2)
def pre_tokenizer(path: str, most: int = 1_000_000) -> PreTokenizer:
    """One for each worker and vocabulary; a worker keeps it from task to task. A bare file name is a
    public vocabulary, looked up on the machine of the worker."""
    return PreTokenizer(path if "/" in path else vocabulary(path), most)


def vocabulary(name: str) -> str:
    """The path of a public vocabulary file on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)
