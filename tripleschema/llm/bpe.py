"""Byte-level BPE by a depth-first walk over the trie of distinct words.

A byte-pair encoding has a handy structure: a token sequence is what the merges produce exactly if each pair of
neighbours is what they produce for that pair alone, and every prefix of a word has one encoding.  So the encoding
of a prefix is fixed by its last token and the encoding of the shorter prefix before it.  The distinct words of a
slice form a trie; walking it depth first, each node gets its last token from the states of its ancestors, once for
all words below it.  Sorted words visit the nodes in just that order, so only the last tokens of the current path are in
memory; the ids of a word are read off them backward, and memory and time are linear in a word's length.

Which pairs of tokens are stable is found by running the merges on the two tokens and kept in a bounded table.
"""

from __future__ import annotations

import json
import os
import re
import struct
from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.llm.common import prepare, slices, used

#: The word pattern of byte-level BPE tokenizers.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Characters on which all Unicode versions since 13 agree whether they are letters or numbers.  Texts with others go
#: through the library's own word splitter, which has its Unicode tables built in.
SETTLED = "[\\u0000-\\u0557\\u0590-\\u0887\\u0900-\\u0bff\\u0d00-\\u1fff\\u20a0-\\ua7cd\\ua800-\\uab6b\\uab70-\\uffff\\U0001f000-\\U0001ffff\\U00020000-\\U0002b739]*+"
#: The same words for texts in Latin letters and common punctuation, where the classes can be listed.
LATIN = "[\\x00-\u02af\u2010-\u201f\u2022\u2026\u20ac]*+"
_L, _N, _S = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\u02af", "0-9\xb2\xb3\xb9\xbc\xbd\xbe", "\\t-\\r \x85\xa0"
LATIN_PATTERN = rf" ?[{_L}]++|'(?:s|t|re|ve|m|ll|d)| ?[^{_S}{_L}{_N}]++| ?[{_N}]++|[{_S}]+(?![^{_S}])|[{_S}]+"

WORDS_KEPT = 120_000  # encodings of words in each of the two generations that a worker remembers
LONG = 64  # characters of a word beyond which it is not remembered, so that what is kept is bounded in bytes too
PAIRS_KEPT = 150_000  # stability results it remembers
NEVER = 1 << 62  # the rank after the last merge
TAIL = 4  # last bytes of a prefix by which the lengths of the tokens that may end there are looked up
SLICE = 1 << 20  # bytes of text whose words are held at a time: as objects they take some fifteen times as much


def byte_alphabet() -> dict[str, int]:
    """The printable stand-in of each byte in byte-level vocabularies, inverted."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class WordEncoder:
    """Splits texts into words and remembers the encodings of words; a subclass encodes the words it has not seen."""

    def __init__(self, special: dict[str, int], width: int = 4):
        self.special, self.width = special, width
        self.words = regex.compile(WORD_PATTERN).findall
        self.settled = regex.compile(SETTLED).fullmatch
        self.latin = re.compile(LATIN).fullmatch
        self.latin_words = re.compile(LATIN_PATTERN).findall
        self.at_special = regex.compile("(" + "|".join(map(regex.escape, special)) + ")") if special else None
        self.known: dict[str, bytes] = {}  # by word
        self.older: dict[str, bytes] = {}  # the generation before, from which words in use are taken over
        self._library = None

    def encode_fresh(self, words: set[str]) -> Iterable[tuple[str, bytes]]:
        raise NotImplementedError

    def pack(self, ids: Iterable[int]) -> bytes:
        return np.fromiter(ids, f"<u{self.width}").tobytes()

    def _library_words(self, text: str) -> list[str]:
        """Words as the library cuts them, for texts with characters outside SETTLED."""
        if self._library is None:
            from tokenizers import pre_tokenizers

            self._library = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=True)
        return [text[a:b] for _, (a, b) in self._library.pre_tokenize_str(text)] if text else []

    def split(self, text: str, specials: bool = True) -> list[str]:
        """The words of a text; with ``specials`` the strings of special tokens are words of their own."""
        if specials and self.at_special and any(s in text for s in self.special):
            return [w for part in self.at_special.split(text) for w in ([part] if part in self.special else self.split(part, False))]
        if self.latin(text):
            return self.latin_words(text)
        return self.words(text) if self.settled(text) else self._library_words(text)

    def learn(self, words: Iterable[str], specials: bool) -> list[str]:
        """Make sure that the encodings of all these words are known; those to be forgotten after use."""
        if len(self.known) > WORDS_KEPT:
            self.known, self.older = {}, self.known
        words = {w for w in words if w not in self.known}
        again = words & self.older.keys()
        self.known.update((w, self.older[w]) for w in again)
        words -= again
        if specials:
            for s in words & self.special.keys():
                self.known[s] = self.pack([self.special[s]])
                words.discard(s)
        self.known.update(self.encode_fresh(words))
        return [w for w in words if len(w) > LONG]

    def encode_texts(self, texts: list[str], specials: bool = True) -> list[bytes]:
        """Ids of each text, packed little-endian."""
        split = [self.split(t, specials) for t in texts]
        long = self.learn(set().union(*split), specials)
        get = self.known.__getitem__
        out = [b"".join(map(get, words)) for words in split]
        for w in long:
            del self.known[w]
        return out


class LibraryEncoder(WordEncoder):
    """Words are encoded by the tokenizers library itself."""

    def __init__(self, path: str, width: int = 4):
        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.n_ids = self.tokenizer.get_vocab_size(with_added_tokens=True)
        super().__init__({t.content: i for i, t in self.tokenizer.get_added_tokens_decoder().items()}, width)
        self.tokenizer.encode_special_tokens = True  # special strings are split off before

    def encode_fresh(self, words: set[str]) -> Iterable[tuple[str, bytes]]:
        return self._one_by_one(list(words))

    def encode_column(self, words: pa.StringArray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of them for each word) of words that begin a text or follow a space in it.

        Words with a space before them are cut apart again in a text of such words, so many are encoded at a time."""
        count, parts = np.zeros(len(words), np.int64), []
        spaced = pc.and_(pc.starts_with(words, " "), pc.greater(pc.binary_length(words), 1)).to_numpy(zero_copy_only=False)
        order = np.r_[np.flatnonzero(spaced), np.flatnonzero(~spaced)]
        n = int(spaced.sum())
        words = words.take(pa.array(order))
        for i in range(0, len(words), 2048):
            part = words[i : min(i + 2048, n)] if i < n else words[max(i, n) : i + 2048]
            rest = words[n : i + 2048] if i < n < i + 2048 else None
            if i < n:
                e = self.tokenizer.encode(pc.binary_join(pa.array([part.to_pylist()], pa.list_(pa.string())), "")[0].as_py(), add_special_tokens=False)
                each = np.bincount(np.array(e.word_ids, np.int64))
                if len(each) == len(part):
                    count[i : i + len(part)] = each
                    parts.append(np.array(e.ids, f"<u{self.width}"))
                    part = None
            for some, at in ((part, i), (rest, n)):
                if some is not None:
                    for j, e in enumerate(self.tokenizer.encode_batch_fast(some.to_pylist(), add_special_tokens=False)):
                        count[at + j] = len(e.ids)
                        parts.append(np.array(e.ids, f"<u{self.width}"))
        ids = np.concatenate(parts) if parts else np.zeros(0, f"<u{self.width}")
        stop = np.cumsum(count)
        back = np.empty(len(order), np.int64)
        back[order] = np.arange(len(order))
        size = count[back]
        start = (stop - count)[back]
        at = np.repeat(start - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
        return ids[at], size

    def _one_by_one(self, words: list[str]) -> Iterable[tuple[str, bytes]]:
        for i in range(0, len(words), 4096):
            part = words[i : i + 4096]
            for w, e in zip(part, self.tokenizer.encode_batch_fast(part, add_special_tokens=False), strict=True):
                yield w, self.pack(e.ids)


class TrieEncoder(WordEncoder):
    """Encoder and decoder for a byte-level BPE vocabulary file of the tokenizers library."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        alphabet = byte_alphabet()
        raw = lambda token: bytes(alphabet[c] for c in token)
        vocab = spec["model"]["vocab"]
        self.path = path
        self.bytes_of: dict[int, bytes] = {i: raw(t) for t, i in vocab.items()}
        self.vocab = {b: i for i, b in self.bytes_of.items()}
        self.size = {i: len(b) for i, b in self.bytes_of.items()}
        self.ends = self._lengths_by_end()
        super().__init__({t["content"]: t["id"] for t in spec["added_tokens"]})
        self.bytes_of |= {i: s.encode() for s, i in self.special.items()}
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(spec["model"]["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            self.merges[vocab[a], vocab[b]] = (rank, vocab[a + b])
        self.packed = {i: struct.pack("<I", i) for i in self.bytes_of}
        self.stable: dict[int, bool] = {}  # by first token << 32 | second
        self.runs: dict[int, tuple[tuple, tuple, tuple] | None] = {}

    def _lengths_by_end(self) -> dict[bytes, tuple[int, ...]]:
        """By what a prefix ends in, TAIL bytes or fewer: the lengths of the tokens that may end there, longest first.

        The longest end of a prefix that is among the keys has all of them, as the last bytes of each token are a key."""
        own: dict[bytes, set[int]] = {}
        for token in self.vocab:
            own.setdefault(token[-TAIL:], set()).add(len(token))
        out: dict[bytes, tuple[int, ...]] = {}
        same: dict[tuple[int, ...], tuple[int, ...]] = {}
        for end in sorted(own, key=len):
            shorter = next((out[end[i:]] for i in range(1, len(end)) if end[i:] in out), ())
            lengths = tuple(sorted({*own[end], *shorter}, reverse=True))
            out[end] = same.setdefault(lengths, lengths)
        return out

    # -- merges

    def _atoms(self, raw: bytes) -> list[int]:
        return [self.vocab[raw[i : i + 1]] for i in range(len(raw))]

    def run(self, t: int) -> tuple[tuple, tuple, tuple] | None:
        """How merges make a token of its bytes: their ranks in order and NEVER, and the first and the last token before
        each and at the end; None if they do not make it."""
        if t in self.runs:
            return self.runs[t]
        ids = self._atoms(self.bytes_of[t])
        ranks, first, last = [], [ids[0]], [ids[-1]]
        while len(ids) > 1:
            found = [(m[0], i, m[1]) for i, pair in enumerate(zip(ids, ids[1:])) if (m := self.merges.get(pair))]  # noqa: B905
            if not found:
                break
            rank, at, new = min(found)
            ids[at : at + 2] = [new]
            ranks.append(rank)
            first.append(ids[0])
            last.append(ids[-1])
        known = self.runs[t] = ((*ranks, NEVER), tuple(first), tuple(last)) if ids == [t] else None
        return known

    def is_whole(self, t: int) -> bool:
        return self.run(t) is not None

    def is_stable(self, a: int, b: int) -> bool:
        """Whether merges make just these two tokens of their bytes: each is made as if alone, and whenever a merge of one
        or the other is next, none across them comes before it (of equal ranks, the leftmost is first)."""
        if (known := self.stable.get(a << 32 | b)) is None:
            if len(self.stable) >= PAIRS_KEPT:
                self.stable.clear()
            known = self.stable[a << 32 | b] = self._apart(self.run(a), self.run(b))
        return known

    def _apart(self, left: tuple | None, right: tuple | None) -> bool:
        if left is None or right is None:
            return False
        (ranks, _, ends), (others, begins, _) = left, right
        i = j = 0
        while True:
            one, other = ranks[i], others[j]
            across = self.merges.get((ends[i], begins[j]))
            if across and across[0] < one and across[0] <= other:
                return False
            if one <= other:
                if one == NEVER:
                    return True
                i += 1
            else:
                j += 1

    # -- the trie

    def encode_words(self, words: Iterable[bytes]) -> Iterator[tuple[bytes, bytes]]:
        """(word, ids as little-endian 32-bit integers) for distinct words, in sorted order."""
        vocab, stable, ends, size, packed = self.vocab.get, self.stable.get, self.ends.get, self.size, self.packed
        last = [-1]  # by depth of the path: the last token of the prefix, which points back to where it begins
        before = b""
        for word in sorted(words):
            n, top = 0, min(len(word), len(before))
            if word[:top] == before[:top]:
                n = top
            else:
                while word[n] == before[n]:
                    n += 1
            del last[n + 1 :]
            for depth in range(n + 1, len(word) + 1):
                at = depth - TAIL if depth > TAIL else 0
                while (lengths := ends(word[at:depth])) is None:
                    at += 1
                for length in lengths:
                    start = depth - length
                    if start < 0:
                        continue
                    t = vocab(word[start:depth])
                    if t is None:
                        continue
                    if start:
                        p = last[start]
                        ok = stable(p << 32 | t)
                        if ok is None:
                            ok = self.is_stable(p, t)
                    else:
                        ok = self.is_whole(t)
                    if ok:
                        break
                last.append(t)
            out, at = [], len(word)
            while at:
                out.append(packed[last[at]])
                at -= size[last[at]]
            out.reverse()
            yield word, b"".join(out)
            before = word

    def encode_fresh(self, words: set[str]) -> Iterable[tuple[str, bytes]]:
        return ((w.decode(), ids) for w, ids in self.encode_words(w.encode() for w in words))

    def decode(self, ids: bytes) -> str:
        """The text of packed ids; bytes that are no UTF-8 become replacement characters."""
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist())).decode("utf-8", "replace")


_encoder = lru_cache(maxsize=2)(TrieEncoder)
library_encoder = lru_cache(maxsize=2)(LibraryEncoder)


def encoder(path: str) -> TrieEncoder:
    """One encoder for each worker process and vocabulary, while it is in use."""
    used(_encoder)
    return _encoder(path)


def _encode_batches(path: str, specials: bool, decode: bool) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for part in slices(batches, limit=SLICE):
            ids = enc.encode_texts([t or "" for t in part.column(1).to_pylist()], specials)
            cols = [part.column(0), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary())]
            names = ["doc_id", "n_tokens", "ids"]
            if decode:
                cols.append(pa.array([enc.decode(x) for x in ids], pa.string()))
                names.append("decoded")
            yield pa.RecordBatch.from_arrays(cols, names)

    return run


def _decode_batches(path: str) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for part in slices(batches):
            out = [None if x is None else enc.decode(x) for x in part.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out, pa.string())], ["doc_id", "decoded"])

    return run


def encode(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", specials: bool = True, decoded: bool = False) -> DataFrame:
    """Token ids of whole texts: ``doc_id, n_tokens, ids`` (binary, little-endian 32-bit), and ``decoded`` on request.

    One narrow pass, no shuffle.  Null and empty texts have no tokens; null ids and repeated rows pass through, row by
    row; other columns of ``docs`` are not read; an empty table gives an empty result.  ``specials=False`` treats the
    strings of special tokens as ordinary text.
    """
    prepare(docs.sparkSession)
    schema = "doc_id long, n_tokens long, ids binary" + ", decoded string" * decoded
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_encode_batches(tokenizer_path, specials, decoded), schema)


def decode(encoded: DataFrame, tokenizer_path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """The texts of packed ids: ``doc_id, decoded``; null ids give null."""
    prepare(encoded.sparkSession)
    return encoded.select(F.col(id_col).alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(_decode_batches(tokenizer_path), "doc_id long, decoded string")
