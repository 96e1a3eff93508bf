"""Exact tokenisation by distinct words, with a bounded cache.

The tokenizer drops white space and never joins across it, so a text's ids are
its words' ids end to end.  A column of texts is split and its words numbered by
Arrow.  Distinct words of ASCII letters are cut from their outer punctuation and
lower-cased, as the tokenizer does itself; the distinct pieces are looked up and
their ids spread over the words by NumPy gathers.  New pieces of letters are
encoded many at a time in one text and told apart by the end-of-word mark of their
last id; everything unusual goes through the tokenizer as it stands.
"""

from __future__ import annotations

import os

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .workers import keep_cache, take_over

WORD_CACHE = 1_000_000
_JOINED = 2000
_OUTER = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
_PLAIN_LIMIT = "ɐ"
_CUT = "^(?P<head>[[:punct:]]*)(?P<core>[A-Za-z]+)(?P<tail>[[:punct:]]*)$"


def plain_parts(word: str) -> int:
    """How many pieces a plain word is cut into before it is encoded: punctuation, letters, punctuation; 0 if not plain."""
    right = word.rstrip(_OUTER)
    core = right.lstrip(_OUTER)
    if not core.isalpha() or "<|" in word:
        return 0
    if not core.isascii():  # folding may yield marks, which the tokenizer treats like punctuation
        folded = core.lower()
        if max(core) >= _PLAIN_LIMIT or len(folded) != len(core) or not folded.isalpha():
            return 0
    head = len(right) - len(core)
    if head == 1 and word[0] == "'":  # may be read as a contraction
        return 0
    return 1 + (head > 0) + (len(right) < len(word))


def _spread(data: np.ndarray, size: np.ndarray, index: np.ndarray) -> np.ndarray:
    """The runs of ``data`` (of sizes ``size``) that ``index`` names, end to end."""
    many = size[index]
    shift = (np.cumsum(size) - size)[index] - (np.cumsum(many) - many)
    return data[np.repeat(shift, many) + np.arange(int(many.sum()))]


class WordEncoder:
    """Encodes texts with a white-space-dropping, lower-casing BPE of the ``tokenizers`` library."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.young: dict[str, bytes] = {"": b""}
        self.old: dict[str, bytes] = {}
        self.closes = self._flags(lambda core, token: core != token)

    def _flags(self, test) -> np.ndarray:
        flags = np.zeros(self.tokenizer.get_vocab_size(with_added_tokens=True), dtype=bool)
        for token, i in self.tokenizer.get_vocab(with_added_tokens=False).items():
            flags[i] = test(token.removesuffix("</w>"), token)
        return flags

    def _ids(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, dtype="<u4") for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _resolve(self, missing: list[str]) -> None:
        plain, parts, odd = [], [], []
        for word in missing:
            if many := plain_parts(word):
                plain.append(word), parts.append(many)
            else:
                odd.append(word)
        chunks = [plain[lo : lo + _JOINED] for lo in range(0, len(plain), _JOINED)]
        for k, (chunk, ids) in enumerate(zip(chunks, self._ids([" ".join(c) for c in chunks]))):
            last = np.cumsum(parts[k * _JOINED : k * _JOINED + len(chunk)]) - 1
            ends = np.flatnonzero(self.closes[ids]) + 1
            if len(ends) != last[-1] + 1:
                odd += chunk
                continue
            data, at = ids.tobytes(), [0, *(4 * ends[last]).tolist()]
            self.young.update((word, data[a:b]) for word, a, b in zip(chunk, at, at[1:]))
        self.young.update(zip(odd, (x.tobytes() for x in self._ids(odd))))

    def _look_up(self, words: list[str]) -> list[bytes]:
        if len(self.young) > WORD_CACHE // 2:
            self.old, self.young = self.young, {"": b""}
        found = list(map(self.young.get, words))
        missing = [word for word, ids in zip(words, found) if ids is None]
        if missing:
            again = list(map(self.old.get, missing))
            self.young.update((word, ids) for word, ids in zip(missing, again) if ids is not None)
            self._resolve([word for word, ids in zip(missing, again) if ids is None])
            found = list(map(self.young.__getitem__, words))
        return found

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts end to end, and how many each text has; null texts have none."""
        split = pc.ascii_split_whitespace(texts.fill_null(""))
        words = split.flatten().dictionary_encode()
        distinct = words.dictionary
        cut = pc.extract_regex(distinct, _CUT)
        head, core, tail = (pc.struct_field(cut, k) for k in range(3))
        # an apostrophe before letters may begin a contraction, "<|" a special token
        plain = pc.invert(pc.or_(pc.equal(head, "'"), pc.match_substring(distinct, "<|"))).fill_null(False)
        none = pa.scalar("", distinct.type)
        pieces = pa.concat_arrays([pc.if_else(plain, head, none), pc.if_else(plain, pc.ascii_lower(core), distinct), pc.if_else(plain, tail, none)]).dictionary_encode()
        found = self._look_up(pieces.dictionary.to_pylist())
        data = np.frombuffer(b"".join(found), "<u4")
        size = np.fromiter(map(len, found), np.int64, len(found)) // 4
        order = pieces.indices.to_numpy().reshape(3, -1).T.ravel()  # each word's three pieces
        data = _spread(data, size, order)
        size = size[order].reshape(-1, 3).sum(1)
        index = words.indices.to_numpy()
        ends = np.concatenate([[0], np.cumsum(size[index])])
        return _spread(data, size, index), np.diff(ends[split.offsets.to_numpy()])

    def sentence_ends(self) -> np.ndarray:
        """For each id, whether it closes a sentence: final punctuation at a word's end."""
        return self._flags(lambda core, token: core != token and core[-1:] in (".", "!", "?"))


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    """One encoder a worker process and file, so its cache outlives a task."""
    take_over("packing")
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    keep_cache("packing", _encoders.clear)
    return _encoders[path]
