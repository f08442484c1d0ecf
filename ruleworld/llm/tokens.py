"""Token ids of a public tokenizer, with a bounded memo of chunks.

A byte-level pre-tokenizer never joins what stands before a space with a space that a non-space character follows.
So a text is cut there into chunks, and a text's ids are its chunks' ids in a row. A batch of texts is cut, its
distinct chunks are found, signs are taken off the ends of words and the words are looked up in the memo, all by Arrow
kernels: the memo holds its keys as one Arrow array and their ids as one array of numbers, so that a key costs some
tens of bytes and no object. Of keys that are not in the memo, words of Latin letters go to the library's merge model, the others
to the whole tokenizer, many as one text in which each starts with a space; the ids come apart again at the tokens that
start with one. The ids of a batch are then gathered as one array. The memo has two generations: when the younger is
full it becomes the elder, and what the elder still gives is taken over, so keys in use stay. Texts that hold the
string of an added token are given to the full tokenizer, as are all texts of tokenizers of another kind; the first
texts of each process are encoded both ways and compared.
"""

from __future__ import annotations

import gc
import json
import re
import sys

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from ruleworld.llm.ship import trim

_CUT = re.compile(r" (?=\S)")
#: First characters that are surely no white space.
_SURE = r"^[!-~\x{A1}-\x{24F}]"
_SIGNS = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
_LETTERS = r"[A-Za-z\x{AA}\x{B5}\x{BA}\x{C0}-\x{D6}\x{D8}-\x{F6}\x{F8}-\x{24F}]+"
#: Letters alone, below U+0250; after a line's end or not.
_WORD = rf"^\n?{_LETTERS}$"
#: Two words, each with signs or not, of two lines.
_LINES = rf"^{_LETTERS}[!-/:-@\[-`{{-~]*\n{_LETTERS}[!-/:-@\[-`{{-~]*$"
#: Signs after a word up to which they are taken off it.
_TAIL = 8


def public_vocabulary(name: str) -> str:
    """Place of a vocabulary file on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_letters() -> dict[int, int]:
    """The byte-level alphabet: printable bytes stand for themselves, the others for code points from 256 on."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    hidden = [b for b in range(256) if b not in shown]
    return {b: 256 + k for k, b in enumerate(hidden)}


def encoder(vocabulary: str, memo: int = 300_000) -> Encoder:
    """This process's encoder of a vocabulary: a worker keeps its memo from task to task."""
    kept = sys.__dict__.setdefault("_ruleworld_encoders", {})
    if vocabulary not in kept:
        kept[vocabulary] = Encoder(vocabulary)
    kept[vocabulary].limit = memo
    return kept[vocabulary]


def forget() -> None:
    """Drop this process's encoders: a worker that turns to other work gives their memory back."""
    sys.__dict__.pop("_ruleworld_encoders", None)
    trim()


def gathered(flat: np.ndarray, size: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Runs of ``flat`` (of the sizes ``size``, one after another) in the order of ``codes``, and the end of each."""
    start = np.cumsum(size) - size
    own = size[codes]
    ends = np.cumsum(own)
    return flat[np.repeat(start[codes] - (ends - own), own) + np.arange(ends[-1] if len(ends) else 0)], ends


class Runs:
    """Keys and the ids of each, one after another."""

    def __init__(self, keys: pa.Array | None = None, flat: np.ndarray | None = None, size: np.ndarray | None = None):
        self.keys = pa.array([], pa.large_string()) if keys is None else keys
        self.flat = np.zeros(0, "<u4") if flat is None else flat
        self.size = np.zeros(0, np.int64) if size is None else size

    def __len__(self) -> int:
        return len(self.size)

    def find(self, keys: pa.Array) -> np.ndarray:
        """Places of keys; -1 where there is none."""
        return np.array(pc.fill_null(pc.index_in(keys, value_set=self.keys), -1), np.int64)

    def plus(self, *others: Runs) -> Runs:
        parts = [x for x in (self, *others) if len(x)]
        if len(parts) < 2:
            return parts[0] if parts else self
        return Runs(pa.concat_arrays([x.keys for x in parts]), np.concatenate([x.flat for x in parts]), np.concatenate([x.size for x in parts]))

    def take(self, places: np.ndarray) -> Runs:
        return Runs(self.keys.take(pa.array(places)), gathered(self.flat, self.size, places)[0], self.size[places])


class Encoder:
    """Encodes texts to little-endian unsigned 32-bit ids."""

    def __init__(self, vocabulary: str, memo: int = 300_000, longest: int = 64, probes: int = 4):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # one task, one core
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import CharDelimiterSplit

        path = public_vocabulary(vocabulary) if "/" not in vocabulary else vocabulary
        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            told = json.load(f)
        kind = told.get("pre_tokenizer") or {}
        self.chunked = kind.get("type") == "ByteLevel" and not kind.get("add_prefix_space") and kind.get("use_regex", True) and not told.get("normalizer") and told["model"]["type"] == "BPE"
        self.added = [t["content"] for t in told.get("added_tokens", [])]
        self.size = self.tokenizer.get_vocab_size()
        self.limit, self.longest, self.probes = memo, longest, probes
        self.young, self.elder = Runs(), Runs()  # words and other chunks that a space leads, without it
        #: whether a token starts with a space, which the byte-level alphabet shows as the letter U+0120
        self.spaced = np.zeros(self.size, bool)
        for token, i in self.tokenizer.get_vocab().items():
            self.spaced[i] = token.startswith("\u0120")
        self.line = self.tokenizer.token_to_id("\u010a")  # a line's end
        self.tails = Runs()  # signs that may follow a word
        self.alphabet = np.arange(256, dtype="<u4")
        for b, c in byte_letters().items():
            self.alphabet[b] = c
        self.alphabet[10] = 10  # between words
        self.merges = Tokenizer(self.tokenizer.model)
        self.merges.pre_tokenizer = CharDelimiterSplit("\n")

    def whole(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _merged(self, words: list[str], at_once: int = 20_000) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words that a space leads, by the merge model, in its byte-level alphabet, and how many each has."""
        out = []
        for k in range(0, len(words), at_once):
            part = words[k : k + at_once]
            raw = np.frombuffer((" " + "\n ".join(part)).encode(), np.uint8)
            shown = self.alphabet[raw].tobytes().decode("utf-32-le")
            out.append(self._apart(self.merges.encode_batch_fast([shown], add_special_tokens=False)[0].ids, len(part)) or self._each([" " + w for w in part]))
        return self._rows(out)

    def _patterned(self, chunks: list[str], at_once: int = 20_000) -> tuple[np.ndarray, np.ndarray]:
        """Ids of chunks that a space leads, by the whole tokenizer, and how many each has."""
        out = []
        for k in range(0, len(chunks), at_once):
            part = chunks[k : k + at_once]
            ids = self.tokenizer.encode_batch_fast([" " + " ".join(part)], add_special_tokens=False)[0].ids
            out.append(self._apart(ids, len(part)) or self._each([" " + c for c in part]))  # None: one holds another space
        return self._rows(out)

    def _apart(self, ids: list[int], parts: int) -> tuple[np.ndarray, np.ndarray] | None:
        """Ids and the number of each part's, cut where a token starts with a space; None if that gives another number of parts."""
        ids = np.array(ids, "<u4")
        first = np.flatnonzero(self.spaced[ids])
        return (ids, np.diff(first, append=len(ids))) if len(first) == parts and first[0] == 0 else None

    def _each(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of texts, each by itself, and how many each has."""
        ids, ends = self._joined(self.whole(texts))
        return ids, np.diff(ends, prepend=0)

    def _rows(self, parts: list) -> tuple[np.ndarray, np.ndarray]:
        if not parts:
            return np.zeros(0, "<u4"), np.zeros(0, np.int64)
        return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])

    def _lined(self, words: list[str], at_once: int = 20_000) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words that a line's end leads, and how many each has."""
        out = []
        for k in range(0, len(words), at_once):
            part = words[k : k + at_once]
            ids = np.array(self.tokenizer.encode_batch_fast(["".join(part)], add_special_tokens=False)[0].ids, "<u4")
            first = np.flatnonzero(ids == self.line)
            out.append((ids, np.diff(first, append=len(ids))) if len(first) == len(part) and first[0] == 0 else self._each(part))
        return self._rows(out)

    def _known(self, keys: pa.Array, kind: np.ndarray) -> tuple[Runs, np.ndarray]:
        """Runs that hold all of some distinct keys, through the memo, and the keys' places there. Kinds: words, words of a new line, others."""
        young, elder = self.young, self.elder
        at = young.find(keys)
        missing = np.flatnonzero(at < 0)
        old = elder.find(keys.take(pa.array(missing)))
        held = old >= 0
        kept = elder.take(old[held])
        at[missing[held]] = len(young) + np.arange(len(kept))
        missing = missing[~held]
        missing = missing[np.argsort(kind[missing], kind="stable")]
        fresh, (words, lined) = keys.take(pa.array(missing)), np.searchsorted(kind[missing], [1, 2]).tolist()
        parts = [self._merged(fresh[:words].to_pylist()), self._lined(fresh[words:lined].to_pylist()), self._patterned(fresh[lined:].to_pylist())]
        at[missing] = len(young) + len(kept) + np.arange(len(missing))
        new = Runs(fresh, *self._rows(parts))
        every = young.plus(kept, new)
        short = pc.binary_length(fresh).to_numpy(zero_copy_only=False) <= self.longest
        self.young = every if short.all() else young.plus(kept, new.take(np.flatnonzero(short)))
        if len(self.young) > self.limit:
            self.elder, self.young = self.young, Runs()
        return every, at

    def _tails(self, chunks: pa.Array, length: np.ndarray) -> np.ndarray:
        """Places in ``tails`` of the signs that end chunks, which have so many of them."""
        at = np.zeros(len(chunks), np.int64)
        if len(self.tails) > 10_000:
            self.tails = Runs()
        for n in np.unique(length).tolist():
            own = np.flatnonzero(length == n)
            cut = (pc.utf8_slice_codeunits(chunks.take(pa.array(own)), start=-n) if n else pa.array([""] * len(own), pa.large_string())).dictionary_encode()
            places = self.tails.find(cut.dictionary)
            new = np.flatnonzero(places < 0)
            if len(new):
                places[new] = len(self.tails) + np.arange(len(new))
                fresh = cut.dictionary.take(pa.array(new))
                self.tails = self.tails.plus(Runs(fresh, *self._each(fresh.to_pylist())))
            at[own] = places[cut.indices.to_numpy()]
        return at

    def _runs(self, chunks: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of distinct chunks that a space leads, and how many each has. Latin letters, and ASCII signs after them, need no pattern."""
        lines = pc.match_substring_regex(chunks, _LINES)
        one, two = chunks.filter(pc.invert(lines)), chunks.filter(lines)
        ends = pc.split_pattern(two, "\n").values  # two a chunk
        second = pc.binary_join_element_wise(pa.scalar("\n", pa.large_string()), ends.take(pa.array(np.arange(1, len(ends), 2))), pa.scalar("", pa.large_string()))
        pieces = pa.concat_arrays([one, ends.take(pa.array(np.arange(0, len(ends), 2))), second])
        stems = pc.utf8_rtrim(pieces, characters=_SIGNS)
        length = pc.subtract(pc.binary_length(pieces), pc.binary_length(stems)).to_numpy(zero_copy_only=False)
        word = pc.match_substring_regex(stems, _WORD).to_numpy(zero_copy_only=False)
        word[: len(one)] &= length[: len(one)] <= _TAIL
        cut = pc.if_else(pa.array(word), stems, pieces).dictionary_encode()
        code = cut.indices.to_numpy()
        kind = np.full(len(cut.dictionary), 2, np.int8)
        kind[code[word]] = 0  # a piece that is no word and signs is never the same as a word
        kind[code[len(pieces) - len(second) :]] = 1
        runs, at = self._known(cut.dictionary, kind)
        tail = self._tails(pieces, np.where(word, length, 0))
        both = np.stack([at[code], len(runs) + tail], 1)
        order = np.full((len(chunks), 4), len(runs) + len(self.tails))  # of no ids
        of = lines.to_numpy(zero_copy_only=False)
        order[~of, :2] = both[: len(one)]
        order[of, :2], order[of, 2:] = both[len(one) : len(one) + len(two)], both[len(one) + len(two) :]
        ids, done = gathered(np.concatenate([runs.flat, self.tails.flat]), np.concatenate([runs.size, self.tails.size, [0]]), order.ravel())
        return ids, np.diff(done[3::4], prepend=0)

    def arrays(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and where each text's end."""
        if not texts:
            return np.zeros(0, "<u4"), np.zeros(0, np.int64)
        if not self.chunked:
            return self._joined(self.whole(texts))
        special = [any(a in t for a in self.added) for t in texts]
        plain = [t for t, s in zip(texts, special, strict=True) if not s]
        ids, ends = self._plain(plain)
        if any(special):
            rest = iter(self.whole([t for t, s in zip(texts, special, strict=True) if s]))
            own = iter(np.split(ids, ends[:-1]) if len(ends) else [])
            ids, ends = self._joined([next(rest) if s else next(own).tobytes() for s in special])
        if self.probes:
            n = min(self.probes, len(texts))
            self.probes -= n
            if b"".join(self.whole(texts[:n])) != ids[: ends[n - 1]].tobytes():
                self.chunked = False
                return self.arrays(texts)
        return ids, ends

    def _joined(self, parts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        return np.frombuffer(b"".join(parts), "<u4"), np.cumsum([len(p) // 4 for p in parts])

    def _plain(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        if not texts:
            return np.zeros(0, "<u4"), np.zeros(0, np.int64)
        parts = pc.split_pattern(pa.array(texts, pa.large_string()), " ")
        cut = parts.values.dictionary_encode()
        chunks, codes, number = cut.dictionary, cut.indices.to_numpy(), np.diff(parts.offsets.to_numpy())
        last = np.cumsum(number)
        first = last - number
        # a space that no non-space follows is no cut: texts with one are cut anew
        doubtful = np.flatnonzero(~pc.match_substring_regex(chunks, _SURE).to_numpy(zero_copy_only=False))
        wrong = np.zeros(len(chunks), bool)
        wrong[[k for k, c in zip(doubtful.tolist(), chunks.take(pa.array(doubtful)).to_pylist(), strict=True) if not c or c[0].isspace()]] = True
        torn = wrong[codes]
        torn[first] = False
        if torn.any():
            return self._torn(texts, set(np.repeat(np.arange(len(texts)), number)[torn].tolist()))
        ids, size = self._runs(chunks.filter(pa.array(~wrong)) if wrong.any() else chunks)
        at = np.cumsum(~wrong) - 1  # a wrong chunk can only be the first of its text here
        head, head_size = self._each(chunks.take(pa.array(codes[first])).to_pylist())
        codes = at[codes]
        codes[first] = len(size) + np.arange(len(first))
        ids, ends = gathered(np.concatenate([ids, head]), np.concatenate([size, head_size]), codes)
        return ids, ends[last - 1]

    def _torn(self, texts: list[str], torn: set[int]) -> tuple[np.ndarray, np.ndarray]:
        """Texts of which some hold spaces in a row, or before a line's end."""
        ids, ends = self._plain([t for k, t in enumerate(texts) if k not in torn])
        own = iter(np.split(ids, ends[:-1]) if len(ends) else [])
        names: dict[str, int] = {}
        cuts = []
        for k in sorted(torn):
            head, *rest = _CUT.split(texts[k])
            cuts.append((head, [names.setdefault(c, len(names)) for c in rest]))
        flat, size = self._runs(pa.array(list(names), pa.large_string()))
        told = [x.tobytes() for x in np.split(flat, np.cumsum(size)[:-1])] if len(size) else []
        heads = iter(self.whole([h for h, _ in cuts]))
        again = iter(cuts)
        return self._joined([next(heads) + b"".join([told[c] for c in next(again)[1]]) if k in torn else next(own).tobytes() for k in range(len(texts))])

    def encode(self, texts: list[str]) -> list[bytes]:
        ids, ends = self.arrays(texts)
        raw, ends = ids.tobytes(), (4 * ends).tolist()
        return [raw[a:b] for a, b in zip([0, *ends[:-1]] if ends else [], ends, strict=True)]

    def stream(self, texts, at_once: int = 2000, chars: int = 8_000_000):
        """Ids of each text of an iterable, in order, as bytes, encoding bounded batches; null is the empty text."""
        part: list[str] = []
        size, collecting = 0, gc.isenabled()
        gc.disable()  # nothing here is cyclic, and the many small objects would set the collector off again and again
        try:
            for t in texts:
                t = t or ""
                if len(t) > chars:  # in segments, of which all but the first start with a space
                    yield from self.encode(part)
                    part, size = [], 0
                    yield b"".join(b for s in self._segments(t, chars) for b in self.encode([s]))
                    continue
                part.append(t)
                size += len(t)
                if len(part) == at_once or size > chars:
                    yield from self.encode(part)
                    part, size = [], 0
            yield from self.encode(part)
        finally:
            if collecting:
                gc.enable()

    def _segments(self, text: str, chars: int):
        if not self.chunked or any(a in text for a in self.added):
            yield text
            return
        at = 0
        while len(text) - at > chars:
            cut = _CUT.search(text, at + chars)
            if cut is None:
                break
            yield text[at : cut.start()]
            at = cut.start()
        yield text[at:]
