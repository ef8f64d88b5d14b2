"""Encoding of many texts at once by their distinct parts between blanks.

Byte-level BPE cuts a text into pieces before it merges, and a blank or a line end that isn't inside a longer run of
white space begins a piece. So the texts of a slice are cut before each of these in Arrow, each distinct part is encoded
once, and the texts' ids are gathered from the parts' ids. Texts in which such a cut could fall inside a piece are
encoded whole. Nothing is kept from one slice to the next, which bounds the memory by the slice.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: All that any of Python, RE2 or the library may take for white space.
SPACE = r"[\s\x0b\x1c-\x1f\x{85}\p{Z}\x{180e}\x{200b}\x{feff}]"
#: Marks whose run after a letter is a piece of its own, so that a word and the marks after it are encoded apart.
MARKS = ".,;:!?$%&*#|"
#: Letters in every version of Unicode.
LETTERS = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZßàáâäçèéêëìíîïñòóôöùúûü"
#: Bytes of text that are encoded together.
SLICE = 32 << 20


def slices(texts: pa.Array, limit: int = SLICE) -> Iterator[tuple[int, int]]:
    """Begins and sizes of runs of texts that have up to ``limit`` bytes each, or one text more."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at = 0
    while at < len(ends):
        before = int(ends[at - 1]) if at else 0
        n = max(1, int(np.searchsorted(ends, before + limit, "right")) - at)
        yield at, n
        at += n


def lists_of(raw: list[bytes]) -> pa.ListArray:
    """Arrays of 32-bit integers from their little-endian bytes."""
    ends = np.cumsum([0] + [len(x) // 4 for x in raw])
    return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(np.frombuffer(b"".join(raw), "<i4")))


def ragged(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The positions of runs of ``sizes`` that begin at ``starts``, one run after the other."""
    before = np.cumsum(sizes) - sizes
    return np.repeat(starts - before, sizes) + np.arange(int(sizes.sum()))


class PartCoder:
    """Encodes Arrow arrays of texts by ``whole`` (ids of each text as bytes) and ``parts`` (an array of ids for each string
    of an array; each string begins with the only blank or line end in it)."""

    def __init__(self, whole: Callable[[list[str]], list[bytes]], parts: Callable[[pa.StringArray], pa.ListArray], special: list[str]):
        self.whole, self.parts = whole, parts
        self.odd = "|".join([rf"{SPACE}[ \n](?:{SPACE}|\z)", rf"\A(?:{SPACE}|\z)", *map(re.escape, special)])
        self.lead = whole(["\n"])[0]

    def encode(self, texts: pa.Array, end: int | None = None) -> pa.ListArray:
        """The ids of each text (null: empty), followed by ``end`` where one is given."""
        texts = pc.fill_null(texts, "")
        odd = pc.match_substring_regex(texts, self.odd) if len(self.lead) == 4 else pa.array(np.ones(len(texts), bool))
        n_odd = pc.sum(odd).as_py() or 0
        tail = b"" if end is None else int(end).to_bytes(4, "little")
        if n_odd == len(texts):
            return lists_of([x + tail for x in self.whole(texts.to_pylist())])
        if not n_odd:
            return self._by_parts(texts, end)
        both = pa.concat_arrays([self._by_parts(texts.filter(pc.invert(odd)), end), lists_of([x + tail for x in self.whole(texts.filter(odd).to_pylist())])])
        is_odd = odd.to_numpy(zero_copy_only=False)
        return both.take(pa.array(np.where(is_odd, len(texts) - n_odd + np.cumsum(is_odd) - 1, np.cumsum(~is_odd) - 1)))

    def _by_parts(self, texts: pa.Array, end: int | None) -> pa.ListArray:
        cut = pc.split_pattern(pc.binary_join_element_wise("\n", pc.replace_substring(texts, "\n", " \n"), ""), " ")
        words = cut.values.dictionary_encode()
        made = self._distinct(words.dictionary).take(words.indices)
        ends = made.offsets.to_numpy()[cut.offsets.to_numpy()]
        # each text's first id is that of the line end that was put before it
        flat = made.values.to_numpy()
        if end is None:
            flat = np.delete(flat, ends[:-1])
            ends = ends - np.arange(len(ends), dtype=np.int32)
        else:
            flat = np.append(flat[1:], flat[:1])
            flat[ends[1:] - 1] = end
        return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(flat))

    def _distinct(self, names: pa.StringArray) -> pa.ListArray:
        """Ids of each part; those without a line end in front stand for themselves with a blank in front."""
        core = pc.utf8_rtrim(names, MARKS)
        core = pc.if_else(pc.match_substring_regex(core, f"[{LETTERS}]\\z"), core, names)
        size, ends = (pc.binary_length(x).to_numpy() for x in (core, names)), np.frombuffer(names.buffers()[1], np.int32)[names.offset + 1 : names.offset + len(names) + 1]
        size = np.subtract(*list(size)[::-1]).astype(np.int32)
        marks = np.frombuffer(names.buffers()[2], np.uint8)[ragged(ends - size, size)] if size.any() else np.empty(0, np.uint8)
        marks = pa.StringArray.from_buffers(len(size), pa.py_buffer(np.append(0, np.cumsum(size)).astype(np.int32)), pa.py_buffer(marks))
        core = pc.binary_join_element_wise(pc.if_else(pc.starts_with(core, "\n"), "", " "), core, "")
        both = pa.concat_arrays([core, marks]).dictionary_encode()
        usual = pc.match_substring_regex(both.dictionary, rf"\A[ \n](?:[^\s\x0b\x1c-\x1f\x{{85}}\p{{Z}}\x{{180e}}\x{{200b}}\x{{feff}}])+\z")
        found = pa.concat_arrays([self.parts(both.dictionary.filter(usual)), lists_of(self.whole(both.dictionary.filter(pc.invert(usual)).to_pylist()))])
        usual = usual.to_numpy(zero_copy_only=False)
        place = np.where(usual, np.cumsum(usual) - 1, usual.sum() + np.cumsum(~usual) - 1).astype(np.int32)
        rows = place[both.indices.to_numpy()].reshape(2, -1).T.ravel()
        made = found.take(pa.array(rows))
        return pa.ListArray.from_arrays(pa.array(made.offsets.to_numpy()[::2]), made.values)
