"""Whole-text encoding through a bounded memo of chunks.

The pre-tokenisers here never let a match run from a non-space character into
the space after it.  A text can therefore be cut before every single space that
follows a non-space character, each chunk encoded alone, and the ids joined.
Chunks repeat far more than texts do, so most cost one dictionary probe.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: A space with white space on both sides: cutting there could change a match.
_UNSAFE = re.compile(r"\s (?=\s|\Z)|\A (?=\s|\Z)")
#: An empty piece, or one that ends in white space, in the pattern language of Arrow.
_SPACE_AT_END = "(?:^|[" + "".join(f"\\x{{{ord(c):x}}}" for c in map(chr, range(0x3001)) if c.isspace()) + "])$"
_SAFE_CUT = re.compile(r"(?<=\S)(?= )")


def simple_words(chunk: str) -> tuple[str, ...] | None:
    """The pre-tokens of a chunk that is a space, letters and perhaps one mark; None for any other shape."""
    if chunk[:1] == " ":
        if chunk[1:].isalpha():
            return (chunk,)
        if chunk[-1] in ".,!?;:" and chunk[1:-1].isalpha():
            return chunk[:-1], chunk[-1]
    return None


#: Characters of a batch for :class:`ChunkEncoder`: large, so that a batch has few distinct chunks.
ENCODER_BATCH = 16_000_000


class ChunkEncoder:
    """Maps texts to 32-bit ids through a bounded memo of chunks.

    ``encode_many`` gives the ids of a list of chunks, exactly as inside a
    text: all ids one after the other and how many each chunk has.  Texts that
    hold one of the strings ``uncut`` are not cut at all.  Chunks that follow a
    space are split, made distinct and looked up by Arrow's hash kernels, and
    ids are gathered by numpy, so only chunks that the memo lacks cost
    interpreted steps.  The memo is a column of words with their ids side by
    side; beyond ``capacity`` words it starts anew with the batch at hand,
    which only costs time.
    """

    def __init__(self, encode_many: Callable[[list[str]], tuple[np.ndarray, np.ndarray]], capacity: int = 2_000_000, uncut: Sequence[str] = ()):
        self.encode_many, self.capacity, self.uncut = encode_many, capacity, uncut
        self._forget()

    def _forget(self) -> None:
        self.words = pa.array([], pa.string())
        self.ids = np.zeros(0, np.uint32)
        self.at = np.zeros(1, np.int32)

    def _places(self, distinct: pa.Array) -> np.ndarray:
        """Places in the memo of distinct chunks, which it learns if need be."""
        if len(self.words) + len(distinct) > self.capacity:
            self._forget()
        found = pc.index_in(distinct, value_set=self.words)
        place = found.fill_null(-1).to_numpy()
        missing = place < 0
        new = distinct.filter(pa.array(missing))
        if len(new):
            place = place.copy()
            place[missing] = np.arange(len(self.words), len(self.words) + len(new))
            ids, n = self.encode_many(pc.binary_join_element_wise("", new, " ").to_pylist())
            self.words = pa.concat_arrays([self.words, new])
            self.ids = np.concatenate([self.ids, ids])
            self.at = np.concatenate([self.at, self.at[-1] + np.cumsum(n, dtype=np.int32)])
        return place

    def encode_flat(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts one after the other, and where each starts and the last ends; call it with a few dozen megabytes at most."""
        if not texts:
            return np.zeros(0, np.uint32), np.zeros(1, np.int64)
        column = pa.array(texts, pa.string())
        pieces = pc.split_pattern(column, " ")
        bounds = pieces.offsets.to_numpy()
        coded = pieces.flatten().dictionary_encode()
        chunk, distinct = coded.indices.to_numpy(), coded.dictionary
        # where a space follows white space the regular expression decides whether the text may be cut
        doubt = pc.match_substring_regex(distinct, _SPACE_AT_END).to_numpy(zero_copy_only=False)
        whole = np.zeros(len(texts), bool)
        for x in self.uncut:
            whole |= pc.match_substring(column, x).to_numpy(zero_copy_only=False)
        odd = {i for i in np.nonzero(np.bitwise_or.reduceat(doubt[chunk], bounds[:-1]))[0].tolist() if _UNSAFE.search(texts[i])} | set(np.nonzero(whole)[0].tolist())
        # the first chunk of a text follows no space; odd texts are cut at safe places only, or not at all
        heads: dict[str, int] = {}
        runs = [[t] if w else _SAFE_CUT.split(t) if i in odd else [t.split(" ", 1)[0]] for i, (t, w) in enumerate(zip(texts, whole.tolist(), strict=True))]
        first = np.fromiter((heads.setdefault(x, len(heads)) for run in runs for x in run), np.int32)
        head_ids, head_n = self.encode_many(list(heads))
        start, size = np.empty(len(chunk), np.int32), np.empty(len(chunk), np.int32)
        after = np.ones(len(chunk), bool)
        after[bounds[:-1]] = False
        for i in odd:
            after[bounds[i] : bounds[i + 1]] = False
        used = np.zeros(len(distinct), bool)
        used[chunk[after]] = True
        place = np.zeros(len(distinct), np.int32)
        place[used] = self._places(distinct.filter(pa.array(used)))
        if len(self.words):
            at = self.at + np.int32(len(head_ids))
            start, size = at[:-1][place][chunk], np.diff(at)[place][chunk]
        size[~after] = 0
        head_at = np.concatenate([[0], np.cumsum(head_n)])
        lead = np.concatenate([[0], np.cumsum([len(run) for run in runs])])
        ids = np.concatenate([head_ids, self.ids])
        start[bounds[:-1]], size[bounds[:-1]] = head_at[first[lead[:-1]]], head_n[first[lead[:-1]]]
        extra = sorted(i for i in odd if len(runs[i]) > 1)
        if extra:
            # the whole of an odd text that was cut stands where its first chunk was
            spots = [first[lead[i] : lead[i + 1]] for i in extra]
            joined = [np.concatenate([head_ids[head_at[k] : head_at[k + 1]] for k in run]) for run in spots]
            n = np.array([len(x) for x in joined])
            start[bounds[extra]], size[bounds[extra]] = len(ids) + np.cumsum(n) - n, n
            ids = np.concatenate([ids, *joined])
        ends = np.zeros(len(chunk) + 1, np.int64)
        np.cumsum(size, out=ends[1:])
        if ends[-1] < 1 << 31:
            where = np.arange(ends[-1], dtype=np.int32)
            where += np.repeat(start - ends[:-1].astype(np.int32), size)
        else:
            where = np.arange(ends[-1]) + np.repeat(start - ends[:-1], size)
        return ids[where], ends[bounds]

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian id bytes of each text."""
        ids, at = self.encode_flat(texts)
        raw = ids.astype("<u4", copy=False).tobytes()
        cut = (4 * at).tolist()
        return [raw[a:b] for a, b in zip(cut, cut[1:], strict=False)]


def batches_by_size(texts: list[str], limit: int = 2_000_000):
    """Index ranges of ``texts`` of at most ``limit`` characters, or one text that is longer."""
    lo = size = 0
    for i, t in enumerate(texts):
        if size and size + len(t) > limit:
            yield lo, i
            lo, size = i, 0
        size += len(t)
    if lo < len(texts):
        yield lo, len(texts)
