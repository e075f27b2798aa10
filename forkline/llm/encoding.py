"""Fast use of a public ``tokenizers`` vocabulary, with the very ids that the library gives.

* Byte-level files: merged by tiktoken under ranks taken from the same file. A probe compares
  both libraries' ids at the start; where they differ, the tokenizers library does the work.
* Files that drop white space: no pre-token spans a space, so the ids of a text are those of
  its space-separated pieces in a row, and pieces are cached. New ones are encoded many in a
  call, by tiktoken under the file's merges where their characters are of common scripts (and
  a probe agrees), else by the tokenizers library.
"""

from __future__ import annotations

import json
import os
import unicodedata
from collections.abc import Callable

import numpy as np

from forkline.llm.common import give_back, tokenizer_file

#: Pieces in each of the two generations of a worker's cache, and the longest that is kept.
GENERATION, CACHED_CHARS = 500_000, 48


_PROBE = " the Word don't 12345 naïve ßtraße ééé... \n  two  spaces\ttab %%% θλ 漢字 zzzzqqqq\n\n\nend "


def _byte_letters() -> dict[str, int]:
    """The letter that stands for each byte in byte-level vocabulary files: itself if it prints, else the next from U+0100."""
    prints = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(prints)]
    return {chr(b): b for b in prints} | {chr(256 + i): b for i, b in enumerate(rest)}


def _merger(path: str, tokenizer) -> Callable[[str], np.ndarray] | None:
    """tiktoken's encoder of a byte-level file whose ids are its merge ranks, or None."""
    try:
        import tiktoken
    except ImportError:
        return None
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    if (spec.get("pre_tokenizer") or {}).get("type") != "ByteLevel" or spec.get("normalizer"):
        return None
    import public_tokenizers

    letters, special = _byte_letters(), {t["content"] for t in spec["added_tokens"]}
    ranks = {bytes(letters[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
    fast = tiktoken.Encoding("from-file", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_to_numpy
    return fast if fast(_PROBE).tolist() == tokenizer.encode(_PROBE, add_special_tokens=False).ids else None


class WordEndMerger:
    """tiktoken for a byte-level file with word ends, over text of code points below U+0530 (beyond, the two libraries class some unassigned ones apart).

    The word end is a private-use character after each pre-token. Its bytes merge first, then
    with the byte before, which gives the file's letter with its word end; all other merges
    follow in the file's order, and ranks are turned into ids at the end.
    """

    END, BELOW = "\U0010fffd", "\u0530"

    def __init__(self, path: str, tokenizer):
        import regex
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        suffix, letters, vocab = spec["model"]["end_of_word_suffix"], _byte_letters(), spec["model"]["vocab"]
        splits = [p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split"]
        if not suffix or len(splits) != 1 or not splits[0]["invert"] or splits[0]["behavior"] != "Removed":
            raise ValueError("not a vocabulary of this kind")
        end = self.END.encode()
        spell = lambda t: bytes(letters[c] for c in t.removesuffix(suffix)) + (end if t.endswith(suffix) else b"")
        order = [bytes([b]) for b in range(256)] + [end[:k] for k in range(2, len(end) + 1)]
        order += [bytes([b]) + end for b in range(256)]
        for m in spec["model"]["merges"]:
            a, b = m if isinstance(m, list) else m.split(" ")
            order.append(spell(a) + spell(b))
        ids = {spell(t): i for t, i in vocab.items() if t not in {x["content"] for x in spec["added_tokens"]}}
        if len(set(order)) != len(order):
            raise ValueError("a merge spells the word end")
        self.to_id = np.array([ids.get(t, -1) for t in order])
        self.merge = tiktoken.Encoding("from-file", pat_str=f"[^{self.END}]+{self.END}", mergeable_ranks={t: i for i, t in enumerate(order)}, special_tokens={}).encode_to_numpy
        self.cut = regex.compile(splits[0]["pattern"]["Regex"]).findall
        self.normalize = tokenizer.normalizer.normalize_str

    def __call__(self, text: str) -> np.ndarray:
        # below U+0530 Python lower-cases like the file's normaliser, but for the final sigma
        plain = unicodedata.is_normalized("NFC", text) and "\u03a3" not in text
        cut = self.cut(text.lower() if plain else self.normalize(text))
        return self.to_id[self.merge(self.END.join([*cut, ""]))] if cut else np.zeros(0, np.int64)


class Encoder:
    """Ids of texts as little-endian bytes of ``dtype``."""

    def __init__(self, vocabulary: str, dtype: str = "<u4"):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(tokenizer_file(vocabulary))
        self.tokenizer.encode_special_tokens = True
        self.vocabulary_size = self.tokenizer.get_vocab_size()
        self.dtype, self.step = dtype, np.dtype(dtype).itemsize

    def ids(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def whole(self, text: str) -> bytes:
        return np.array(self.ids(text), dtype=self.dtype).tobytes()

    def __call__(self, texts: list[str]) -> list[bytes]:
        return [self.whole(t) for t in texts]


class MergedEncoder(Encoder):
    """For a byte-level vocabulary: tiktoken under the ranks of the same file."""

    def __call__(self, texts: list[str]) -> list[bytes]:
        return [self.merge(t).astype(self.dtype).tobytes() for t in texts]


class PieceEncoder(Encoder):
    """For a vocabulary that drops white space: ids of space-separated pieces, kept in two bounded generations."""

    MARK = "\x00"

    def __init__(self, vocabulary: str, dtype: str = "<u4"):
        super().__init__(vocabulary, dtype)
        self.mark_id = self.ids(f"a {self.MARK} b")[1]
        self.new: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        try:
            fast = WordEndMerger(tokenizer_file(vocabulary), self.tokenizer)
            probe = "".join(c for c in _PROBE if c < fast.BELOW)
            upper = " ".join(chr(c) for c in range(33, 0x530) if chr(c).isprintable())
            agree = all(fast(x).tolist() == self.ids(x) for x in (probe, upper))
            self.fast = fast if agree else None
        except (ImportError, ValueError, KeyError):
            self.fast = None

    def _learn(self, pieces: list[str]) -> dict[str, bytes]:
        """Ids of many pieces in one call, parted by a mark that no piece holds."""
        out: dict[str, bytes] = {}
        plain = [p for p in pieces if self.MARK not in p and p.strip()]
        if self.fast is not None:
            self._bulk([p for p in plain if max(p) < self.fast.BELOW], self.fast, out)
        self._bulk([p for p in plain if p not in out], self.ids, out)
        for p in pieces:
            if p not in out:
                out[p] = self.whole(p)
        return out

    def _bulk(self, plain: list[str], encode, out: dict[str, bytes]) -> None:
        for i in range(0, len(plain), 4000):
            some = plain[i : i + 4000]
            ids = np.asarray(encode(f" {self.MARK} ".join(some)), dtype=self.dtype)
            cuts = (np.flatnonzero(ids == self.mark_id) * self.step).tolist()
            if len(cuts) != len(some) - 1:
                continue
            flat, at = ids.tobytes(), 0
            for p, cut in zip(some, [*cuts, len(flat)], strict=True):
                out[p] = flat[at:cut]
                at = cut + self.step

    def __call__(self, texts: list[str]) -> list[bytes]:
        pieces = [t.replace("\n", " ").split(" ") for t in texts]
        missing = set().union(*pieces).difference(self.new)
        if missing:
            again = {p: self.old[p] for p in missing if p in self.old}
            self.new.update(again)
            self.new.update(self._learn(list(missing.difference(again))))
        out = [b"".join(map(self.new.__getitem__, own)) for own in pieces]
        for p in missing:
            if len(p) > CACHED_CHARS:
                del self.new[p]
        if len(self.new) > GENERATION:
            self.old, self.new = self.new, {}
        return out


_encoders: dict[tuple[str, str], Encoder] = {}


def encoder(vocabulary: str, dtype: str = "<u4") -> Encoder:
    """This worker's encoder; its cache lasts over tasks."""
    key = (vocabulary, dtype)
    if key not in _encoders:
        plain = Encoder(vocabulary, dtype)
        merge = _merger(tokenizer_file(vocabulary), plain.tokenizer)
        if merge is not None:
            plain = MergedEncoder(vocabulary, dtype)
            plain.merge, plain.tokenizer = merge, None  # no longer needed
        elif not plain.ids(" ") and plain.ids("a b") == plain.ids("a") + plain.ids("b"):
            plain = PieceEncoder(vocabulary, dtype)
        _encoders[key] = plain
        give_back()  # what the files' parsers used
    return _encoders[key]
