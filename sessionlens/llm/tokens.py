"""Public tokenizers run over whole texts in Arrow batches, through a bounded memo of text units.

A text is cut at boundaries that no token can cross, and each unit between two boundaries is encoded by the
library once for as long as the memo, an array of fixed size, holds it. The boundaries are safe for these reasons:

* byte-level BPE (``tokenizers``): its pattern starts a new piece at a single space that stands between two
  characters that are not white space, and at a single line feed between two such characters. Units keep the space
  in front of them; special strings hold no white space and so lie inside a unit, where the library finds them.
* piece BPE (``sentencepiece``): no piece of the vocabulary has a word mark after another character (checked when
  the model is loaded), so no merge crosses a character followed by a space. The space that the cut removes comes
  back as the mark that the library puts in front of every text.

Texts of any length are so split into units of bounded work; results equal those of one call on the whole text.
"""

from __future__ import annotations

import os
import re
from array import array
from collections.abc import Callable, Sequence
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import UnitCache

#: Ids of a unit that the memo holds; units with more are encoded each time.
FEW = 7

#: White space next to a space or a line feed, or at either end: such a text takes the slower, careful way.
_WHITE = r"[\p{Z}\x09-\x0d\x1c-\x1f\x{85}]"
_ODD = rf"[ \n]{_WHITE}|{_WHITE}[ \n]|\A[ \n]|[ \n]\z"
_CAREFUL = re.compile(r"(?<=\S)([ \n])(?=\S)")
_PIECE_CUT = re.compile("(?<=[^ ▁]) (?!\\Z)")
_BREAK = "\n"
#: The byte-level alphabet: printable bytes stand for themselves, the others in turn for code points from 256 on.
_PRINTED = {*range(33, 127), *range(161, 173), *range(174, 256)}
_OTHERS = [b for b in range(256) if b not in _PRINTED]
_ALPHABET = {b: chr(b) for b in _PRINTED} | {b: chr(256 + i) for i, b in enumerate(_OTHERS)}
#: Letters up to this one are letters in every Unicode version at hand.
_LAST = "\u024f"
_BYTES = {c: "".join(_ALPHABET[b] for b in chr(c).encode()) for c in range(ord(_LAST) + 1)}
#: ASCII marks, without the apostrophe, that stand behind a word.
_MARKS = "".join(chr(c) for c in range(33, 127) if not chr(c).isalnum() and chr(c) != "'")


def _file(name: str) -> str:
    if os.path.isabs(name):
        return name
    import public_tokenizers

    return public_tokenizers.path(name)


class ByteBpe:
    """Encodes texts as little-endian ids, each ``width`` bytes wide, exactly as the library does without added specials."""

    def __init__(self, name: str, entries: int = 1 << 20):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.lib = Tokenizer.from_file(_file(name))
        self.kind = np.dtype("<u2") if self.lib.get_vocab_size(with_added_tokens=True) <= 1 << 16 else np.dtype("<u4")
        self.code = "H" if self.kind.itemsize == 2 else "I"
        pre = self.lib.pre_tokenizer
        #: Plain letters with or without marks behind them can go straight to the library's merges.
        self.direct = self.lib.normalizer is None and type(pre).__name__ == "ByteLevel" and not pre.add_prefix_space and not self.lib.model.dropout
        self.tails: dict[str, list[int]] = {"": []}
        #: A key that begins with a line feed is a unit that follows one; any other follows a space. A row: how many ids, the ids.
        self.memo = UnitCache(1 + FEW, self.kind, entries)
        self.feed = self._plain([_BREAK])[0]

    def _plain(self, units: Sequence[str]) -> list[bytes]:
        return [np.asarray(e.ids, self.kind).tobytes() for e in self.lib.encode_batch_fast(list(units), add_special_tokens=False)]

    def _make_keys(self, keys: Sequence[str]) -> list[bytes]:
        after = [k[:1] == _BREAK for k in keys]
        got = self._make([k[1:] if a else " " + k for k, a in zip(keys, after, strict=True)])
        return [self.feed + g if a else g for g, a in zip(got, after, strict=True)]

    def _make(self, units: Sequence[str]) -> list[bytes]:
        out: list = [None] * len(units)
        plain = []
        merge, tails = self.lib.model.tokenize, self.tails
        for k, unit in enumerate(units):
            base = unit.rstrip(_MARKS)
            word = base[1:] if base[:1] == " " else base
            if not (self.direct and word.isalpha() and max(word) <= _LAST and len(word) < 200):
                plain.append(k)
                continue
            tail = unit[len(base) :]
            if tail not in tails:
                if len(tails) > 10_000:
                    tails.clear()
                tails[tail] = [t.id for t in merge(tail)]
            out[k] = array(self.code, [t.id for t in merge(base.translate(_BYTES))] + tails[tail]).tobytes()
        for k, got in zip(plain, self._plain([units[k] for k in plain]), strict=True):
            out[k] = got
        return out

    def _known(self, keys: Sequence[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """An array of ids, where in it the ids of each key begin, and how many they are."""
        hit, rows, hashes = self.memo.get(keys)
        lens, starts = rows[:, 0].astype(np.int64), np.arange(len(keys), dtype=np.int64) * FEW
        new = np.flatnonzero(~hit)
        made = self._make_keys([keys[i] for i in new.tolist()])
        more = np.frombuffer(b"".join(made), self.kind)
        lens[new] = n = np.fromiter(map(len, made), np.int64, len(made)) // self.kind.itemsize
        starts[new] = begins = len(keys) * FEW + np.cumsum(n) - n
        short = np.flatnonzero(n <= FEW)
        put = np.zeros((len(short), 1 + FEW), self.kind)
        put[:, 0] = n[short]
        for k in range(FEW):
            some = n[short] > k
            put[some, 1 + k] = more[(begins[short] - len(keys) * FEW)[some] + k]
        self.memo.put(hashes[new[short]], put)
        return np.concatenate([rows[:, 1:].ravel(), more]), starts, lens

    def encode(self, texts: Sequence[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts one after another, and where each text begins and the last ends."""
        given = arrow(texts)
        odd = np.flatnonzero(pc.match_substring_regex(given, _ODD).to_numpy(zero_copy_only=False))
        plain = pc.replace_substring(given, _BREAK, " " + _BREAK)
        lists = pc.split_pattern(pc.binary_join_element_wise(pa.scalar(_BREAK, pa.large_string()), plain, pa.scalar("", pa.large_string())), " ")
        if len(odd):
            careful = {}
            for k in odd.tolist():
                parts = _CAREFUL.split(given[k].as_py())
                careful[k] = [_BREAK + parts[0], *(_BREAK + u if cut == _BREAK else u for cut, u in zip(parts[1::2], parts[2::2], strict=True))]
            whole = lists.to_pylist()
            lists = pa.array([careful.get(k, whole[k]) for k in range(len(given))], lists.type)
        units = pc.dictionary_encode(lists.values)
        ids, starts, lens = self._known(units.dictionary.to_numpy(zero_copy_only=False).tolist())
        at = units.indices.to_numpy(zero_copy_only=False)
        flat, ends = gather(ids, starts, lens, at)
        offsets = np.concatenate([[0], ends])[np.asarray(lists.offsets)]
        heads = len(self.feed) // self.kind.itemsize  # of the line feed put before each text
        cut = np.ones(len(flat), bool)
        cut[(offsets[:-1, None] + np.arange(heads)).ravel()] = False
        return flat[cut], offsets - heads * np.arange(len(offsets))


def arrow(texts) -> pa.Array:
    """An Arrow array of texts; nulls are empty."""
    given = texts if isinstance(texts, pa.Array) else pa.array(texts, pa.large_string())
    return pc.fill_null(given.cast(pa.large_string()), "")


def gather(values: np.ndarray, starts: np.ndarray, lens: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """values[starts[i] : starts[i] + lens[i]] for every i of ``at``, one after another, and where each ends."""
    n = lens[at]
    ends = np.cumsum(n)
    places = np.repeat(starts[at] - (ends - n), n)
    places += np.arange(len(places))
    return values[places], ends


class PieceBpe:
    """Counts the pieces of texts exactly as the library gives them, without begin and end marks."""

    def __init__(self, name: str, entries: int = 1 << 20):
        import sentencepiece

        self.lib = sentencepiece.SentencePieceProcessor(model_file=_file(name))
        pieces = (self.lib.id_to_piece(i) for i in range(self.lib.get_piece_size()))
        plain = self.lib.encode("a  b", out_type=str) + self.lib.encode("", out_type=str) == ["▁a", "▁", "▁b"]
        self.cut = plain and not any("▁" in p.lstrip("▁") or " " in p for p in pieces)
        self.memo = UnitCache(1, np.dtype(np.uint32), entries)

    def count(self, texts: Sequence[str]) -> list[int]:
        if not self.cut:
            return [len(x) for x in self.lib.encode(arrow(texts).to_pylist(), num_threads=1)]
        given = arrow(texts)
        odd = np.flatnonzero(pc.match_substring_regex(given, "  |▁|\\A | \\z").to_numpy(zero_copy_only=False))
        lists = pc.split_pattern(given, " ")
        if len(odd):
            careful = {k: _PIECE_CUT.split(given[k].as_py()) for k in odd.tolist()}
            whole = lists.to_pylist()
            lists = pa.array([careful.get(k, whole[k]) for k in range(len(given))], lists.type)
        units = pc.dictionary_encode(lists.values)
        keys = units.dictionary.to_numpy(zero_copy_only=False).tolist()
        hit, rows, hashes = self.memo.get(keys)
        lens, new = rows[:, 0].astype(np.int64), np.flatnonzero(~hit)
        lens[new] = [len(x) for x in self.lib.encode([keys[i] for i in new.tolist()], num_threads=1)]
        self.memo.put(hashes[new], lens[new, None].astype(np.uint32))
        sums = np.concatenate([[0], np.cumsum(lens[units.indices.to_numpy(zero_copy_only=False)])])
        return np.diff(sums[np.asarray(lists.offsets)]).tolist()


class PlainCount:
    """Counts the ids of a ``tokenizers`` file: the lengths of what ``ByteBpe`` gives, or of plain calls for other kinds."""

    def __init__(self, name: str, entries: int = 1 << 20):
        self.byte = ByteBpe(name, entries)
        self.cut = self.byte.direct

    def count(self, texts: Sequence[str]) -> list[int]:
        if self.cut:
            return np.diff(self.byte.encode(texts)[1]).tolist()
        return [len(e.ids) for e in self.byte.lib.encode_batch_fast(arrow(texts).to_pylist(), add_special_tokens=False)]


@lru_cache(maxsize=4)
def byte_bpe(name: str) -> ByteBpe:
    return ByteBpe(name)


@lru_cache(maxsize=4)
def counter(name: str) -> Callable[[Sequence[str]], list[int]]:
    return (PlainCount(name) if name.endswith(".json") else PieceBpe(name)).count
