"""Token ids of whole texts as the tokenizers library gives them, with each distinct chunk encoded once per worker.

A byte-level BPE with the usual split pattern never joins a non-space character with a
single space after it, so a text may be cut before every space that stands alone between
two non-space characters, each chunk encoded by itself, and the ids concatenated.  Any
other white space stays inside a chunk.  Chunks are kept in a bounded cache; what falls
out is simply encoded again.

New words of basic letters are merged by tiktoken, which is several times faster, over the same vocabulary: it
merges by the rank of the result, so this is allowed only where a vocabulary numbers its tokens in the
order of its merges (checked when it is loaded).  Words with other characters, texts with
irregular white space and texts that hold a special token's string go to the tokenizers library.
"""

from __future__ import annotations

import json
import os
import re

import numpy as np

#: Chunks kept per Python worker (about 250 MB); they are dropped by halves.
CACHE_CHUNKS = 1_200_000
#: Longer chunks are rare and not worth keeping.
CACHE_CHARS = 40
#: Chunks that the library gets as one text.
JOINT = 2000

_CUT = re.compile(r"(?<=\S)(?= \S)")
#: The split pattern that the tokenizers library's byte-level pre-tokenizer is defined by (a fixed value).
_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Characters below this one (Latin) are of the same class in every version of the character tables.
_BASIC = "\u0250"


def default_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class ChunkEncoder:
    """``encode(texts)`` gives each text's ids as little-endian unsigned 32-bit bytes."""

    _by_path: dict[str, ChunkEncoder] = {}

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        # a byte-level token stands for as many bytes as its name has letters; a special token for its own text
        special = {i: len(t.content.encode()) for i, t in self.tokenizer.get_added_tokens_decoder().items()}
        self.specials = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.widths = np.zeros(self.tokenizer.get_vocab_size(), np.int64)
        for name, i in self.tokenizer.get_vocab().items():
            self.widths[i] = special.get(i, len(name))
        self.merge = _ranked(path, special)
        self.new: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    @classmethod
    def of(cls, path: str) -> ChunkEncoder:
        if path not in cls._by_path:
            cls._by_path[path] = cls(path)
        return cls._by_path[path]

    @staticmethod
    def _clean(word: str) -> bool:
        """Whether single spaces on either side of a word stand between non-space characters."""
        return bool(word) and not word[0].isspace() and not word[-1].isspace()

    def _basic(self, word: str) -> bool:
        return self.merge is not None and (word.isascii() or max(word) < _BASIC)

    def _encode_apart(self, chunks: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch_fast(chunks, add_special_tokens=False)]

    def _encode_words(self, words: list[str]) -> list[bytes]:
        """Ids of clean words with a space before each, many as one text, whose ids are cut where the words' bytes end."""
        if not words:
            return []
        parts = [words[k : k + JOINT] for k in range(0, len(words), JOINT)]
        if self._basic(words[0]):
            ids = np.concatenate([np.frombuffer(self.merge(" " + " ".join(p)), np.uint32) for p in parts])
        else:
            ids = np.concatenate([np.array(e.ids, "<u4") for e in self.tokenizer.encode_batch_fast([" " + " ".join(p) for p in parts], add_special_tokens=False)])
        ends = np.cumsum(self.widths[ids])
        sizes = [len(w) + 1 if w.isascii() else len(w.encode()) + 1 for w in words]
        stops = (4 * (np.searchsorted(ends, np.cumsum(sizes)) + 1)).tolist()
        raw = ids.astype("<u4", copy=False).tobytes()
        return [raw[a:b] for a, b in zip([0, *stops], stops, strict=False)]

    def _whole(self, text: str) -> bytes:
        """A text with other white space beside a space, or with a special token's string: cut with care, nothing kept."""
        if any(s in text for s in self.specials):
            return self._encode_apart([text])[0]
        return b"".join(self._encode_apart(_CUT.split(text)))

    def _firsts(self, words: list[str]) -> list[bytes]:
        """Ids of the words that start a text."""
        out = [np.frombuffer(self.merge(w), np.uint32).astype("<u4", copy=False).tobytes() if w and self._basic(w) else None for w in words]
        rest = [k for k, x in enumerate(out) if x is None]
        for k, ids in zip(rest, self._encode_apart([words[k] for k in rest]), strict=True):
            out[k] = ids
        return out

    def _learn(self, missing: set[str]) -> set[str]:
        """Encode and keep the clean ones of ``missing``; return the others."""
        new, old = self.new, self.old
        for w in [w for w in missing if w in old]:
            new[w] = old[w]
            missing.discard(w)
        clean = [w for w in missing if self._clean(w)]
        basic = [w for w in clean if self._basic(w)]
        for words in (basic, [w for w in clean if not self._basic(w)] if len(basic) < len(clean) else []):
            new.update(zip(words, self._encode_words(words), strict=True))
        return missing.difference(clean)

    def encode(self, texts: list[str]) -> list[bytes]:
        """``new`` and ``old`` hold the ids of words with a space before them, clean words only."""
        if len(self.new) > CACHE_CHUNKS // 2:
            self.old, self.new = self.new, {}
        look, found, holes, missing = self.new.get, [], [], set()
        for t in texts:
            words = t.split(" ")
            first, words[0] = words[0], None
            ids = list(map(look, words))
            at, open_ = 0, []
            for _ in range(ids.count(None) - 1):
                at = ids.index(None, at + 1)
                open_.append((at, words[at]))
                missing.add(words[at])
            found.append(ids)
            holes.append((first, open_))
        odd = self._learn(missing)
        irregular = [bool(odd and not odd.isdisjoint(w for _, w in open_)) or any(s in t for s in self.specials) for t, (_, open_) in zip(texts, holes, strict=True)]
        out = []
        for text, ids, (_, open_), apart, first in zip(texts, found, holes, irregular, self._firsts([f for f, _ in holes]), strict=True):
            if apart:
                out.append(self._whole(text))
                continue
            ids[0] = first
            for at, word in open_:
                ids[at] = look(word)
            out.append(b"".join(ids))
        for w in [w for w in missing if len(w) > CACHE_CHARS]:
            self.new.pop(w, None)
        return out


def _ranked(path: str, special: dict[int, int]):
    """``text -> ids`` (packed, 32 bits in the machine's order) by ranks, or None where ids are not in the order of merges."""
    import tiktoken

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    model, split = spec["model"], spec.get("pre_tokenizer") or {}
    plain = split.get("type") == "ByteLevel" and not split.get("add_prefix_space") and split.get("use_regex", True)
    if model.get("type") != "BPE" or not plain or spec.get("normalizer") or model.get("ignore_merges") or model.get("continuing_subword_prefix") or model.get("end_of_word_suffix"):
        return None
    pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
    made = [model["vocab"].get(a + b) for a, b in pairs]
    if None in made or any(x >= y for x, y in zip(made, made[1:], strict=False)):
        return None
    byte_of = _byte_letters()
    names = {bytes(byte_of[c] for c in name): i for name, i in model["vocab"].items() if i not in special}
    if len(names) < 256 or set(names.values()) != {*made, *(names.get(bytes([b])) for b in range(256))}:
        return None
    core = tiktoken.Encoding("byte-level", pat_str=_PATTERN, mergeable_ranks=names, special_tokens={})._core_bpe
    return lambda text: core.encode_to_tiktoken_buffer(text, set())


def _byte_letters() -> dict[str, int]:
    """The letter that stands for each byte in names of byte-level tokens: printable ones themselves, the others from 256 on."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + k): b for k, b in enumerate(hidden)}
