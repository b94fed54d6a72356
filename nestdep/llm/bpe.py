"""Byte-pair encoding by a prefix-sharing trie, and decoding.

A text is cut at white space; the distinct pieces of a batch are normalised and
split into pre-tokens, and the distinct pre-tokens form a trie.  Walking the
trie depth first, each node gets one state: the last token of the encoding of
the prefix that ends there.  It is the only vocabulary entry that ends the
prefix and stays apart from the state of the node where it begins, so one state
per node gives the encodings of all words, and prefixes that words share are
worked on once.  (Sorted words are the trie in depth-first order: the stack of
states is kept as far as a word agrees with the one before.)

The encoding equals the public tokenizers library's for word-end BPE files:
special tokens in a text are found first, then NFC, white space, lower case,
the pre-token pattern, byte letters, merges.  Decoding joins the vocabulary
strings with one blank, as that library does for files without a decoder.

Defined cases: a null text is empty and has no tokens; repeated rows get equal
results; an empty table gives an empty result; texts are never cut; caches
are bounded and only save time; other columns are ignored.
"""

from __future__ import annotations

import gc
import json
import re
import struct
import sys
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import bounded_batches
from ._text import claim, slices, trim_memory

_CACHE_PIECES = 150_000
_CACHE_PAIRS = 200_000
_ODD_SPACE = re.compile("[\x1c-\x1f]")
_BEYOND_LATIN = re.compile("[^\x00-\u024f]")
_SPACES = regex.compile(r"\p{White_Space}+")


def byte_letters() -> list[str]:
    """The public byte-to-letter table: printable Latin-1 stays, the rest follows from 256 on."""
    stay = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return [chr(b) if b in stay else chr(next(rest)) for b in range(256)]


class WordBpe:
    """A word-end BPE vocabulary read from a tokenizers JSON file."""

    def __init__(self, path: str) -> None:
        self.path, self.library = path, None
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.suffix = model["end_of_word_suffix"] or ""
        self.ids: dict[str, int] = model["vocab"]
        self.text = {i: t for t, i in self.ids.items()}
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.text |= {i: t for t, i in self.special.items()}
        self.strings = [self.text.get(i, "") for i in range(max(self.text) + 1)]
        self.cut_special = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")").split if self.special else None
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.pretokens = regex.compile(split["pattern"]["Regex"].replace(r"\s", r"\p{White_Space}")).findall
        self.letters = {b: c for b, c in enumerate(byte_letters())}
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.rank = {(a, b): r for r, (a, b) in enumerate(pairs)}
        self.made: dict[str, tuple[int, str, str]] = {}
        for r, (a, b) in enumerate(pairs):
            self.made.setdefault(a + b, (r, a, b))
        self.longest = max(map(len, self.ids))
        self.apart: dict[tuple[str, str], bool] = {}
        self.pieces: dict[str, bytes] = {}
        self.words: dict[str, bytes] = {}
        self.whole: dict[str, bool] = {}
        self.four = {t: i.to_bytes(4, "little") for t, i in self.ids.items()}

    # -- states of the trie -------------------------------------------------

    def stays_apart(self, a: str, b: str) -> bool:
        """Do the merges leave tokens a and b, side by side, as they are?

        Undo the later-made of the two at the common border, step by step: if
        the two pieces that meet there would have merged before, they do not.
        """
        known = self.apart.get((a, b))
        if known is not None:
            return known
        if len(self.apart) > _CACHE_PAIRS:
            self.apart.clear()
        left, right, until, good = a, b, len(self.rank) + 1, True
        none = (-1, "", "")
        while True:
            rank = self.rank.get((left, right))
            if rank is not None and rank < until:
                good = False
                break
            was_left, was_right = self.made.get(left, none), self.made.get(right, none)
            if was_left[0] < 0 and was_right[0] < 0:
                break
            if was_left[0] > was_right[0]:
                until, left = was_left[0], was_left[2]
            else:  # of equal merges the left one comes first
                until, right = was_right[0] + 1, was_right[1]
        self.apart[a, b] = good
        return good

    def stands(self, token: str) -> bool:
        """Do the merges make this whole token from its own letters?"""
        known = self.whole.get(token)
        if known is None:
            made = self.made.get(token)
            known = made is None or (self.stands(made[1]) and self.stands(made[2]) and self.stays_apart_before(made))
            self.whole[token] = known
        return known

    def stays_apart_before(self, made: tuple[int, str, str]) -> bool:
        """Are the two parts of a token still apart when their merge comes?"""
        limit, left, right = made
        until, none = limit, (-1, "", "")
        while True:
            was_left, was_right = self.made.get(left, none), self.made.get(right, none)
            if was_left[0] < 0 and was_right[0] < 0:
                return True
            if was_left[0] > was_right[0]:
                until, left = was_left[0], was_left[2]
            else:
                until, right = was_right[0] + 1, was_right[1]
            rank = self.rank.get((left, right))
            if rank is not None and rank < until:
                return False

    def encode_words(self, words: list[str]) -> dict[str, list[str]]:
        """Token strings of each distinct word (in byte letters)."""
        ids, apart, stands, suffix, longest = self.ids, self.stays_apart, self.stands, self.suffix, self.longest
        known = self.apart.get
        cut = len(suffix)
        states: list[str] = [""]  # states[i]: last token of the first i letters
        before, out = "", {}
        for word in sorted(words):
            n = len(word)
            same, most = 0, min(n - 1, len(states) - 1, len(before))
            while same < most and word[same] == before[same]:
                same += 1
            del states[same + 1 :]
            for i in range(same + 1, n):
                for j in range(i - longest if i > longest else 0, i):
                    token = word[j:i]
                    if token in ids:
                        if not j:
                            good = stands(token)
                        elif (good := known((states[j], token))) is None:
                            good = apart(states[j], token)
                        if good:
                            states.append(token)
                            break
                else:
                    raise ValueError(f"no token ends {word[:i]!r}")
            whole = word + suffix
            for j in range(n - longest if n > longest else 0, n):
                token = whole[j:]
                if token in ids:
                    if not j:
                        good = stands(token)
                    elif (good := known((states[j], token))) is None:
                        good = apart(states[j], token)
                    if good:
                        break
            else:
                raise ValueError(f"no token ends {word!r}")
            tokens, i = [token], n + cut - len(token)
            while i:
                token = states[i]
                tokens.append(token)
                i -= len(token)
            tokens.reverse()
            out[word] = tokens
            before = word
        return out

    # -- texts ----------------------------------------------------------------

    def learn(self, pieces: set[str]) -> list[str]:
        """Encode pieces without white space that are not in the cache yet; those beyond its room are returned."""
        letters, pretokens, words, known = self.letters, self.pretokens, self.words, self.pieces
        new = [p for p in pieces if p not in known]
        split, ask = [], set()
        for piece in new:
            if piece.isascii():
                found = pretokens(piece.lower())
            elif _BEYOND_LATIN.search(piece):
                found = self.split_by_library(piece)
            else:
                normal = unicodedata.normalize("NFC", piece).lower()
                found = [w if w.isascii() and w.isprintable() else w.encode().decode("latin-1").translate(letters) for w in pretokens(normal)]
            if not all(w.isprintable() for w in found):
                found = [w if w.isprintable() else w.encode().decode("latin-1").translate(letters) for w in found]
            split.append(found)
            ask.update(found)
        room = _CACHE_PIECES - len(known)
        fresh = [w for w in ask if w not in words]
        for word, tokens in self.encode_words(fresh).items():
            words[word] = b"".join(map(self.four.__getitem__, tokens))
        for piece, found in zip(new, split):
            if len(found) == 1:
                known[piece] = words[found[0]]
            else:
                known[piece] = b"".join([words[w] for w in found])
        if len(words) > _CACHE_PIECES:
            for word in fresh:
                del words[word]
        return new[max(0, room) :]

    def split_by_library(self, piece: str) -> list[str]:
        """Pre-tokens in byte letters, by the file's own normaliser: Unicode versions differ beyond Latin."""
        if self.library is None:
            from tokenizers import Tokenizer

            self.library = Tokenizer.from_file(self.path)
        normal = self.library.normalizer.normalize_str(piece)
        return [w for w, _ in self.library.pre_tokenizer.pre_tokenize_str(normal)]

    def segments(self, text: str) -> list[str]:
        """Texts between special tokens, and these, in turn."""
        if self.cut_special is None or "<|" not in text:
            return [text]
        return self.cut_special(text)

    def cut(self, text: str) -> list[str]:
        return [p for p in _SPACES.split(text) if p] if _ODD_SPACE.search(text) else text.split()

    def encode_batch(self, texts: list[str]) -> list[tuple[int, bytes, str]]:
        """(number of tokens, ids as little-endian unsigned 32-bit, decoded text) of each text."""
        collecting = gc.isenabled()
        gc.disable()  # many small tuples and no cycles
        try:
            return self._encode(texts)
        finally:
            if collecting:
                gc.enable()

    def _encode(self, texts: list[str]) -> list[tuple[int, bytes, str]]:
        cut = [[(s, True) if k % 2 else (self.cut(s), False) for k, s in enumerate(self.segments(t))] for t in texts]
        pieces = {p for parts in cut for s, special in parts if not special for p in s}
        beyond = self.learn(pieces)
        known, out = self.pieces, []
        for parts in cut:
            raw = []
            for s, special in parts:
                raw += [self.special[s].to_bytes(4, "little")] if special else [known[p] for p in s]
            whole = b"".join(raw)
            out.append((len(whole) // 4, whole, self.decode(whole)))
        for piece in beyond:
            del known[piece]
        return out

    def decode(self, raw: bytes) -> str:
        """Vocabulary strings of ids, joined by one blank."""
        return " ".join(map(self.strings.__getitem__, memoryview(raw).cast("I") if sys.byteorder == "little" else struct.unpack(f"<{len(raw) // 4}I", raw)))


_LOADED: dict[str, WordBpe] = {}


def loaded(path: str) -> WordBpe:
    if path not in _LOADED:
        _LOADED[path] = WordBpe(path)
    return _LOADED[path]


def encode_texts(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, n_tokens, token_ids (little-endian uint32), decoded."""
    bounded_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("bpe", _LOADED.clear)
        bpe = None
        for batch in batches:
            bpe = bpe or loaded(vocabulary)
            for part in slices(batch, "text", 1_000_000):
                coded = bpe.encode_batch(part.column("text").to_pylist())
                n, raw, text = zip(*coded)
                out = [part.column("id"), pa.array(n, pa.int64()), pa.array(raw, pa.binary()), pa.array(text, pa.string())]
                del coded, n, raw, text
                yield pa.RecordBatch.from_arrays(out, names=["id", "n_tokens", "token_ids", "decoded"])
        trim_memory()

    base = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return base.mapInArrow(run, f"id {dict(base.dtypes)['id']}, n_tokens long, token_ids binary, decoded string").withColumnRenamed("id", id_col)
