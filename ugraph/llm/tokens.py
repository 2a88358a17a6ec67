"""Fast exact encoding with the vocabulary file of a word-level BPE tokenizer.

The file belongs to the ``tokenizers`` library, which is the definition of the result. Texts made of common
characters are normalised and cut with Arrow string kernels, and their different words are merged by tiktoken's BPE core,
which is given the same file's merges; every other text goes through ``tokenizers`` itself. Both routes give the same ids because every
entry of the vocabulary that normalised text can hold encodes to itself (tests check that and compare both routes).
"""

from __future__ import annotations

import json
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Characters outside this set send a text to the tokenizers library: controls, odd spaces, combining marks,
#: scripts whose case folding needs context, and anything that could open a special token.
UNSAFE = r"[^\t\n\r -~¡-ÿĀ-įıĲ-ɏ‐-‧€]|<\|"
END_ID = 1


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins of byte-level BPE: visible Latin-1 characters stand for themselves, the other
    bytes take code points from 256 on, in order."""
    visible = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(visible)]
    return {chr(b): b for b in visible} | {chr(256 + i): b for i, b in enumerate(hidden)}


class WordEncoder:
    """Encoder of Arrow string arrays. A blank closes each word, as the vocabulary's word-end mark does."""

    def __init__(self, path: str):
        self.path = path
        self._slow = None
        with open(path, encoding="utf-8") as f:
            described = json.load(f)
        vocab = described["model"]["vocab"]
        import tiktoken

        letters = byte_alphabet()
        by_bytes: dict[bytes, int] = {}
        for entry, i in vocab.items():
            closed = entry.endswith("</w>")
            core = entry[:-4] if closed else entry
            if all(c in letters for c in core):
                by_bytes[bytes(letters[c] for c in core) + b" " * closed] = i
        self.size = max([*vocab.values(), *(t["id"] for t in described["added_tokens"])]) + 1
        # Ranks: single bytes, then bytes that close a word (the first merge of any word), then the file's merges.
        ordered = sorted(by_bytes, key=by_bytes.get)
        ranked = [bytes([b]) for b in range(256)]
        ranked += [x for x in ordered if len(x) == 2 and x[1:] == b" "]
        seen = set(ranked)
        ranked += [x for x in ordered if x not in seen]
        self._core = tiktoken.Encoding("words", pat_str=r"[^ ]+ ", mergeable_ranks={x: r for r, x in enumerate(ranked)}, special_tokens={})
        self._ids = np.array([by_bytes.get(x, 0) for x in ranked], dtype=np.uint32)
        self._closes = np.array([x.endswith(b" ") for x in ranked])

    @property
    def library(self):
        if self._slow is None:
            from tokenizers import Tokenizer

            self._slow = Tokenizer.from_file(self.path)
        return self._slow

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids in a row and the bounds of each text's ids (one more than texts). Null counts as empty."""
        texts = pc.fill_null(texts.cast(pa.string()), "")
        odd = pc.match_substring_regex(texts, UNSAFE)
        if not pc.any(odd).as_py():
            return self._quick(texts)
        odd = np.asarray(odd)
        ids, bounds = self._quick(texts.filter(pa.array(~odd)))
        quick = iter(range(len(bounds) - 1))
        parts = []
        for is_odd, text in zip(odd.tolist(), texts, strict=True):
            if is_odd:
                parts.append(np.array(self.library.encode(text.as_py(), add_special_tokens=False).ids, dtype=np.uint32))
            else:
                k = next(quick)
                parts.append(ids[bounds[k] : bounds[k + 1]])
        return np.concatenate([*parts, np.empty(0, np.uint32)]), np.cumsum([0, *map(len, parts)])

    def _quick(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        t = pc.utf8_lower(texts)
        for blank in "\n\t\r":
            t = pc.replace_substring(t, blank, " ")
        t = pc.replace_substring_regex(t, r"(\pL)([^ \pL])", r"\1 \2")
        for _ in range(2):
            t = pc.replace_substring_regex(t, r"(\pN)([^ ])", r"\1 \2")
        short = r"(^| )'(re|ve|ll|[stmd])"
        # \x02 shields the apostrophe of a short form, which stays joined to its letters.
        while pc.any(pc.match_substring_regex(t, short)).as_py():
            t = pc.replace_substring_regex(t, short, "\\1\x02\\2 ")
        t = pc.replace_substring_regex(t, r"([^ \pL\pN\x02])([\pL\pN])", r"\1 \2")
        t = pc.replace_substring(t, "\x02", "'")
        t = pc.replace_substring_regex(t, r"  +", " ")
        t = pc.utf8_trim(t, " ")
        full = pc.not_equal(t, "")
        words = np.where(np.asarray(full), np.asarray(pc.count_substring(t, " ")) + 1, 0)
        coded = pc.split_pattern(t.filter(full), " ").flatten().dictionary_encode()
        if not len(coded):
            return np.empty(0, np.uint32), np.zeros(len(texts) + 1, np.int64)
        # each different word is merged once
        raw = np.frombuffer(self._core._core_bpe.encode_to_tiktoken_buffer(" ".join(coded.dictionary.to_pylist()) + " ", set()), dtype=np.uint32)
        starts = np.concatenate(([0], np.flatnonzero(self._closes[raw]) + 1)).astype(np.int32)
        which = np.asarray(coded.indices)
        lengths = np.diff(starts)[which]
        ends = np.concatenate(([0], np.cumsum(lengths)))
        ids = self._ids[raw][np.repeat(starts[which] - ends[:-1], lengths) + np.arange(ends[-1])]
        return ids, ends[np.concatenate(([0], np.cumsum(words)))]


@cache
def encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


def with_end(ids: np.ndarray, bounds: np.ndarray, end_id: int = END_ID) -> tuple[np.ndarray, np.ndarray]:
    """Append ``end_id`` to every text's ids."""
    return np.insert(ids, bounds[1:], end_id).astype(np.uint32), bounds + np.arange(len(bounds))
