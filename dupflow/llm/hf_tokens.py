"""Ids of a byte-level vocabulary file by the tokenizers library."""

from __future__ import annotations

import os
import re
import sys
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from dupflow.llm.chunks import ChunkEncoder

_CACHE: dict[tuple[str, bool], ChunkEncoder] = {}

#: A space and letters is one pre-token of a byte-level vocabulary, with a point behind it is two.
_WORD, _WORD_AND_POINT = r"^ \p{L}+$", r"^ \p{L}+[.,!?;:]$"
#: Other chunks of at least one character, all of these, are cut into pre-tokens here; any other goes to the library alone.
_COMMON = re.compile(r"[\n -~À-ÖØ-öø-ž]+\Z")
#: Stands between pre-tokens; no chunk cut here holds it.
_CUT = "\x00"


def little_endian(ids: list[int]) -> bytes:
    """Unsigned 32-bit little-endian bytes."""
    a = array("I", ids)
    if sys.byteorder == "big":
        a.byteswap()
    return a.tobytes()


def encoder(path: str, special_as_text: bool = False) -> ChunkEncoder:
    """One encoder for each worker process and vocabulary file, kept between tasks.

    As in the library's own default, the string of a special token inside a
    text is that token; with ``special_as_text`` it is ordinary text.  A text
    that holds such a string is encoded whole.
    """
    key = (path, special_as_text)
    if key not in _CACHE:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import public_tokenizers
        import regex
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel, CharDelimiterSplit, Sequence

        tok = Tokenizer.from_file(path)
        tok.encode_special_tokens = special_as_text
        added = [t.content for t in tok.get_added_tokens_decoder().values()]
        find = regex.compile(public_tokenizers.PATTERN).findall
        # the same model over pre-tokens that are cut already
        by_cut = Tokenizer(tok.model)
        by_cut.pre_tokenizer = Sequence([CharDelimiterSplit(_CUT), ByteLevel(add_prefix_space=False, use_regex=False)])
        known = tok.normalizer is None and isinstance(tok.pre_tokenizer, ByteLevel)

        def joint(pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
            """Ids of pre-tokens one after the other, and how many each has."""
            got, size = [np.zeros(0, np.uint32)], [np.zeros(0, np.int64)]
            for lo in range(0, len(pieces), 4096):
                part = pieces[lo : lo + 4096]
                e = by_cut.encode(_CUT.join(part), add_special_tokens=False)
                got.append(np.array(e.ids, np.uint32))
                size.append(np.bincount(np.array(e.word_ids), minlength=len(part)))
            return np.concatenate(got), np.concatenate(size)

        def with_points(chunks: list[str], words: pa.Array, ids: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """As :func:`joint` for words with a point behind; those whose word is among ``words`` take its ids."""
            bare, last = [c[:-1] for c in chunks], [c[-1] for c in chunks]
            new = sorted({*bare, *last}.difference(words.to_pylist()))
            more_ids, more_n = joint(new)
            words = pa.concat_arrays([words, pa.array(new, pa.string())])
            ids, n = np.concatenate([ids, more_ids]), np.concatenate([n, more_n])
            both = np.stack([pc.index_in(pa.array(x, pa.string()), value_set=words).to_numpy() for x in (bare, last)], 1).ravel()
            start, size = (np.cumsum(n) - n)[both], n[both]
            return ids[np.repeat(start - (np.cumsum(size) - size), size) + np.arange(size.sum())], size.reshape(-1, 2).sum(1)

        def encode_many(chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
            column = pa.array(chunks, pa.string())
            plain = pc.match_substring_regex(column, _WORD).to_numpy(zero_copy_only=False) & known
            marked = pc.match_substring_regex(column, _WORD_AND_POINT).to_numpy(zero_copy_only=False) & known
            got: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
            words, points = np.nonzero(plain)[0], np.nonzero(marked)[0]
            bare = column.filter(pa.array(plain))
            ids, n = joint(bare.to_pylist())
            got.append((words, ids, n))
            if len(points):
                got.append((points, *with_points([chunks[i] for i in points.tolist()], bare, ids, n)))
            rest = np.nonzero(~plain & ~marked)[0].tolist()
            cut = {i: find(chunks[i]) for i in rest if known and _COMMON.match(chunks[i]) and not any(x in chunks[i] for x in added)}
            if cut:
                ids, n = joint([x for c in cut.values() for x in c])
                ends = np.cumsum([len(c) for c in cut.values()])
                got.append((np.array([*cut]), ids, np.diff(np.concatenate([[0], np.cumsum(n)[ends - 1]]))))
            alone = [i for i in rest if i not in cut]
            if alone:
                each = [e.ids for lo in range(0, len(alone), 1024) for e in tok.encode_batch_fast([chunks[i] for i in alone[lo : lo + 1024]], add_special_tokens=False)]
                got.append((np.array(alone), np.array([i for x in each for i in x], np.uint32), np.array([len(x) for x in each])))
            n = np.zeros(len(chunks), np.int64)
            for where, _, size in got:
                n[where] = size
            at = np.concatenate([[0], np.cumsum(n)])
            ids = np.empty(at[-1], np.uint32)
            for where, values, size in got:
                ids[np.repeat(at[where] - (np.cumsum(size) - size), size) + np.arange(len(values))] = values
            return ids, n

        _CACHE[key] = ChunkEncoder(encode_many, uncut=() if special_as_text else added)
    return _CACHE[key]
