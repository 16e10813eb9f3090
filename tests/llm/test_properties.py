"""Properties on generated inputs."""

import numpy as np
import public_tokenizers
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st

from sievework.llm import byte_bpe, packing, simhash, tokens, toxicity, url_filter

RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
CODEC = byte_bpe.Codec(RANKS, public_tokenizers.PATTERN)
LIBRARY = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.load_ranks(RANKS), special_tokens={})
TOKENS = {n: tokens.Tokens(public_tokenizers.path(n)) for n in ("byte_bpe_50k.json", "word_bpe_49k.json")}
TEXT = st.text(st.characters(exclude_categories=("Cs",)), max_size=60)


@settings(max_examples=300, deadline=None)
@given(TEXT)
def test_codec(text):
    packed = CODEC.encode(text)
    assert np.frombuffer(packed, np.uint32).tolist() == LIBRARY.encode_ordinary(text)
    assert CODEC.decode(packed, chunk=2) == text


@settings(max_examples=300, deadline=None)
@given(TEXT)
def test_tokens(text):
    for own in TOKENS.values():
        assert own.encode(text).tolist() == own.by_library([text])[0].tolist()


@settings(max_examples=200, deadline=None)
@given(st.binary(max_size=40), st.integers(1, 7))
def test_utf8_machine_on_any_bytes(data, n):
    machine = byte_bpe.Utf8Machine()
    parts = "".join(machine.feed(data[i : i + n]) for i in range(0, len(data), n)) + machine.finish()
    try:
        assert parts == data.decode()
    except UnicodeDecodeError:
        assert "�" in parts


@settings(max_examples=150, deadline=None)
@given(st.lists(st.integers(1, 64), max_size=80))
def test_packing_places_each_piece_once(lengths):
    bins = packing.pack(lengths, 64)
    assert sorted(i for b in bins for i in b) == list(range(len(lengths)))
    assert all(sum(lengths[i] for i in b) <= 64 for b in bins)
    assert len(bins) >= -(-sum(lengths) // 64)


@given(st.integers(1, 5000), st.integers(1, 512))
def test_cut(n, capacity):
    parts = packing.cut(n, capacity)
    assert sum(k for _, k in parts) == n and [s for s, _ in parts] == list(np.cumsum([0] + [k for _, k in parts])[:-1]) and all(k == capacity for _, k in parts[1:])


@settings(max_examples=200, deadline=None)
@given(st.lists(st.lists(st.integers(0, 9), min_size=3, max_size=3), min_size=1, max_size=4))
def test_allocation_is_least(costs):
    from itertools import product

    costs = [[0.0, *map(float, sorted(c))] for c in costs]
    total = 0
    want = min((sum(costs[i][t + 1] for i, t in enumerate(ts)) for ts in product(range(-1, 3), repeat=len(costs)) if sum(ts) == total), default=None)
    if want is not None:
        assert simhash.allocate(costs, total)[0] == want


@settings(max_examples=200, deadline=None)
@given(TEXT)
def test_fold_is_idempotent(text):
    assert toxicity.fold(toxicity.fold(text)).split() == toxicity.fold(text).split()


def test_fixed_rules():
    assert len(url_filter.RULES) == 4 and url_filter.DEFAULT == "allow"
