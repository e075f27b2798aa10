"""Why tiktoken under a file's merges gives the ids of the tokenizers library.

Both repeat: merge the leftmost pair of least rank. The library knows pairs, tiktoken only
the bytes that a pair makes, so they part only if a token's bytes can also stand as another
pair of neighbours when its rank is due. Nothing outside a pair of neighbours has merged with
what is inside it, so by induction over ranks its inside is in the state that the token's
bytes alone would be in; if the library's merges turn these bytes into the one token, that
state is the listed pair, and no other can occur. The first test shows just that for every
token of both files, and that ranks rise in the order of the merges. What is left is how
texts are cut into pieces, which goes by classes of characters: the second test compares ids
for every code point, in several neighbourhoods.
"""

import json
import random

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from forkline.llm.encoding import MergedEncoder, PieceEncoder, encoder

FILES = {"byte_bpe_50k.json": "<u4", "word_bpe_49k.json": "<u2"}


def library(name):
    plain = Tokenizer.from_file(public_tokenizers.path(name))
    plain.encode_special_tokens = True
    return plain


def merged(symbols, rank):
    """The library's process over one piece: the leftmost listed pair of least rank, again and again."""
    symbols = list(symbols)
    while len(symbols) > 1:
        found = min((rank[p], i) for i, p in enumerate(zip(symbols, symbols[1:], strict=False)) if p in rank) if any(p in rank for p in zip(symbols, symbols[1:], strict=False)) else None
        if found is None:
            break
        i = found[1]
        symbols[i : i + 2] = [symbols[i] + symbols[i + 1]]
    return symbols


@pytest.mark.parametrize("name", FILES)
def test_every_token_comes_from_one_pair(name):
    with open(public_tokenizers.path(name), encoding="utf-8") as f:
        spec = json.load(f)
    model, special = spec["model"], {t["content"] for t in spec["added_tokens"]}
    assert not model.get("dropout") and not model.get("ignore_merges") and not model.get("byte_fallback")
    end = model.get("end_of_word_suffix") or ""
    pairs = [tuple(m if isinstance(m, list) else m.split(" ")) for m in model["merges"]]
    # a symbol with the end of a word is one letter and a mark: spell both as one character more
    mark = "\U0010ffff"
    spell = lambda t: t.removesuffix(end) + mark if end and t.endswith(end) else t
    rank = {(spell(a), spell(b)): i for i, (a, b) in enumerate(pairs)}
    assert len(rank) == len(pairs)
    made = [spell(a) + spell(b) for a, b in pairs]
    assert len(set(made)) == len(made)  # no token has two merges
    vocabulary = {spell(t): i for t, i in model["vocab"].items() if t not in special}
    if isinstance(encoder(name), MergedEncoder):  # its ranks are the ids
        ids = [vocabulary[t] for t in made]
        assert ids == sorted(ids)
    for token in vocabulary:
        first = list(token[:-2]) + [token[-2:]] if token.endswith(mark) else list(token)
        assert merged(first, rank) == [token]


@pytest.mark.parametrize("name", FILES)
def test_every_code_point_is_cut_alike(name):
    plain, mine = library(name), encoder(name, FILES[name])
    assert isinstance(mine, MergedEncoder | PieceEncoder) and getattr(mine, "fast", True) is not None
    points = [c for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    if isinstance(mine, PieceEncoder):  # beyond, the library itself does the work
        points = [c for c in points if c < 0x700]
    for i in range(0, len(points), 20_000):
        texts = [f"a{c}b {c}{c}1 {c}'s\n{c}" for c in map(chr, points[i : i + 20_000])]
        want = [np.array(e.ids, FILES[name]).tobytes() for e in plain.encode_batch(texts, add_special_tokens=False)]
        assert mine(texts) == want


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text(alphabet=st.one_of(st.sampled_from("aeinstr .,'\n\t-*!|09ÄßéñΣσ"), st.characters(exclude_categories=["Cs"])), max_size=60), min_size=1, max_size=4))
def test_random_texts(texts):
    for name, dtype in FILES.items():
        want = [np.array(e.ids, dtype).tobytes() for e in library_of(name).encode_batch(texts, add_special_tokens=False)]
        assert encoder(name, dtype)(texts) == want


_libraries = {}


def library_of(name):
    if name not in _libraries:
        _libraries[name] = library(name)
    return _libraries[name]


@pytest.mark.parametrize("name", FILES)
def test_ids_of_the_given_documents(name):
    import pyarrow.parquet as pq

    texts = [t or "" for t in pq.read_table("/root/testdata/sf0.01/documents.parquet", columns=["text"])["text"].to_pylist()]
    random.Random(3).shuffle(texts)
    want = [np.array(e.ids, FILES[name]).tobytes() for e in library_of(name).encode_batch(texts, add_special_tokens=False)]
    assert encoder(name, FILES[name])(texts) == want
