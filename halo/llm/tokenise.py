"""Token ids of whole texts with the tokenizers library, word by word through a cache.

Both vocabularies used here cut a text before the merges, and always cut it where a visible character
is followed by white space. So a text is split there, each piece is encoded once and its ids are kept
as bytes: the ids of a text are the joined bytes of its pieces. Texts with white space outside ASCII
(where the libraries may disagree about what white space is) are encoded whole.
"""

from __future__ import annotations

import os
import re
import sys
import types

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CACHE_PIECES = 500_000

# Code points (first, last) of white space and joiners outside space, tab, line feed, carriage return.
ODD_RANGES = ((0x0B, 0x0C), (0x1C, 0x1F), (0x85, 0x85), (0xA0, 0xA0), (0x1680, 0x1680), (0x180E, 0x180E), (0x2000, 0x200F), (0x2028, 0x202F), (0x205F, 0x2060), (0x3000, 0x3000), (0xFEFF, 0xFEFF))
ODD_SPACE = re.compile("[" + "".join(f"{chr(a)}-{chr(b)}" for a, b in ODD_RANGES) + "]")
# A run of Latin letters is cut off where ASCII punctuation or white space follows: no vocabulary here joins the two.
# U+0130 is left out: its lower case is a letter and a combining mark, which a vocabulary may split.
_LETTERS = "[A-Za-z" + "".join(f"{chr(a)}-{chr(b)}" for a, b in ((0xC0, 0xD6), (0xD8, 0xF6), (0xF8, 0x12F), (0x131, 0x24F))) + "]+"
_RUN = _LETTERS + "(?=[ \\t\\n\\r.,;:!?'\"|)]|\\Z)"
PIECES = re.compile(f" ?{_RUN}|[ \\t\\n\\r]*[^ \\t\\n\\r]+|[ \\t\\n\\r]+")
# Where words lose their space, letters are cut off at all ASCII digits and punctuation.
WORDS = re.compile(f"{_LETTERS}(?=[ \\t\\n\\r!-@\\[-`{{-~]|\\Z)|[^ \\t\\n\\r]+")
# Lower-casing before the vocabulary's own lower-casing shares cache entries; left out where the two might differ.
NOT_LATIN = re.compile(f"[{chr(0x130)}{chr(0x250)}-{chr(0x10FFFF)}]")


def _shared(owner: str) -> dict:
    """State of this Python worker, kept on a module of its own so that it survives from task to task.

    One operator owns it at a time: workers serve the stages of a pipeline one after another, and the
    caches of past stages would add up.
    """
    state = sys.modules.setdefault("_halo_llm_worker", types.ModuleType("_halo_llm_worker")).__dict__.setdefault("state", {})
    if state.get("owner") != owner:
        state.clear()
        state["owner"] = owner
    return state



class PieceEncoder:
    """Encodes texts with one vocabulary file. `keeps_space`: white space before a word changes its ids."""

    def __init__(self, path: str, keeps_space: bool):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.tokenizer = self.plain = Tokenizer.from_file(path)
        self.pattern = PIECES if keeps_space else WORDS
        self.folds = not keeps_space
        # Ids that close a word (end mark) or open one (leading space).
        names = self.tokenizer.get_vocab(with_added_tokens=False)
        self.edge = np.zeros(self.tokenizer.get_vocab_size(), bool)
        for name, k in names.items():
            self.edge[k] = name.endswith("</w>") if self.folds else name.startswith(chr(0x120))
        self.simple = re.compile(("" if self.folds else " ") + _LETTERS + "\\Z").match
        self.known: dict[str, bytes] = {"": b""}
        if self.folds:  # plain words are composed and end at white space: neither is looked for again
            self.plain = Tokenizer.from_file(path)
            self.plain.normalizer = normalizers.Lowercase()
            self.plain.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])

    @staticmethod
    def of(path: str, keeps_space: bool) -> "PieceEncoder":
        shared, key = _shared("encoder"), ("encoder", path, keeps_space)
        if key not in shared:
            shared[key] = PieceEncoder(path, keeps_space)
        return shared[key]

    def _encode(self, texts: list[str]) -> list[bytes]:
        done = self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)
        return [np.asarray(e.ids, "<u4").tobytes() for e in done]

    def _learn(self, names: list[str]) -> None:
        """Put the ids of new pieces into the cache. Plain words are encoded many to a text, which is faster than one by one."""
        plain, rest = [], []
        for x in names:
            (plain if self.simple(x) else rest).append(x)
        glue = "" if not self.folds else " "
        groups = [plain[k : k + 512] for k in range(0, len(plain), 512)]
        for at in range(0, len(groups), 16):
            part = groups[at : at + 16]
            for words, e in zip(part, self.plain.encode_batch_fast([glue.join(g) for g in part], add_special_tokens=False)):
                ids = np.asarray(e.ids, "<u4")
                mark = self.edge[ids]
                if int(mark.sum()) != len(words):
                    rest += words
                    continue
                where = np.flatnonzero(mark) * 4
                raw = ids.tobytes()
                if self.folds:  # the mark is on a word's last id
                    ends = (where + 4).tolist()
                    starts = [0, *ends[:-1]]
                else:  # on its first
                    starts = where.tolist()
                    ends = [*starts[1:], len(raw)]
                self.known.update(zip(words, [raw[a:b] for a, b in zip(starts, ends)]))
        for k in range(0, len(rest), 8192):
            self.known.update(zip(rest[k : k + 8192], self._encode(rest[k : k + 8192])))

    def encode(self, texts: list[str | None], end_id: int) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text, with `end_id` appended."""
        end = int(end_id).to_bytes(4, "little")
        odd = [bool(t and ODD_SPACE.search(t)) for t in texts]
        even = [t or "" for t, o in zip(texts, odd) if not o]
        made = iter(self._words(even, end) if self.folds else self._pieces(even, end))
        return [self._encode([t])[0] + end if o else next(made) for t, o in zip(texts, odd)]

    def _words(self, texts: list[str], end: bytes) -> list[bytes]:
        """Where words are folded and lose their space: each distinct word is looked up once a call, its ids are laid out by index."""
        known, get = self.known, self.known.__getitem__
        # Without odd white space these are the six separators of ASCII, where the pattern always cuts.
        cut = pc.ascii_split_whitespace(pa.array([t.lower() if t.isascii() or not NOT_LATIN.search(t) else t for t in texts], pa.large_string()))
        named = cut.flatten().dictionary_encode()
        names = named.dictionary.to_numpy(zero_copy_only=False).tolist()
        ids = list(map(known.get, names))
        at = [k for k, x in enumerate(ids) if x is None]
        new = [names[k] for k in at]
        made = {x: parts for x in new if len(parts := self.pattern.findall(x)) > 1}
        fresh = [x for x in set(new).difference(made).union(*made.values()) if x not in known]
        self._learn(fresh)
        known.update([(x, b"".join(map(get, parts))) for x, parts in made.items()])
        fresh += made
        for k, x in zip(at, new):
            ids[k] = known[x]
        self._forget(fresh)
        flat, size = np.frombuffer(b"".join(ids), "<u4"), np.fromiter(map(len, ids), np.int64, len(ids)) // 4
        index = named.indices.to_numpy()
        each = size[index]
        ends = np.cumsum(each)
        place = np.arange(ends[-1] if len(ends) else 0) + np.repeat((np.cumsum(size) - size)[index] - (ends - each), each)
        raw = flat[place].tobytes()
        bounds = (4 * np.concatenate([[0], ends])[cut.offsets.to_numpy()]).tolist()
        return [raw[a:b] + end for a, b in zip(bounds, bounds[1:])]

    def _pieces(self, texts: list[str], end: bytes) -> list[bytes]:
        """Where white space is kept: piece by piece."""
        known, seen, split = self.known, set(), []
        for t in texts:
            pieces = self.pattern.findall(t)
            ids = list(map(known.get, pieces))
            at = [k for k, x in enumerate(ids) if x is None]
            new = [pieces[k] for k in at]
            seen.update(new)
            split.append((ids, at, new))
        fresh, out = list(seen), []
        self._learn(fresh)
        for ids, at, new in split:
            for k, x in zip(at, new):
                ids[k] = known[x]
            ids.append(end)
            out.append(b"".join(ids))
        self._forget(fresh)
        return out

    def _forget(self, fresh: list[str]) -> None:
        """What does not fit into the cache stays for one call only."""
        spare = len(self.known) - CACHE_PIECES
        if spare > 0:
            for x in fresh[-spare:]:
                del self.known[x]


def slices(texts: list, most_chars: int = 4_000_000):
    """Ranges of `texts` with a bounded number of characters (one long text stands alone)."""
    start, size = 0, 0
    for k, t in enumerate(texts):
        n = len(t) if t else 0
        if k > start and size + n > most_chars:
            yield start, k
            start, size = k, 0
        size += n
    if start < len(texts):
        yield start, len(texts)
