"""Suffix sorting and removal, transducer and encoder, against brute force and the library."""

import hashlib
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from linkgraph.llm.bpe import Encoder, Rules, decode, default_tokenizer, encode, unknown_ranges
from linkgraph.llm.lexicon import Lexicon, compile_lexicon
from linkgraph.llm.suffix_dedup import SuffixDedupParams, suffix_dedup
from linkgraph.llm.suffix_sort import common_prefix, deep_shallow


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text("ab", max_size=40).map(str.encode), max_size=30))
def test_deep_shallow_sorts(strings):
    order, lcps = deep_shallow(strings, shallow=3)
    assert sorted(order) == list(range(len(strings)))
    assert [strings[i] for i in order] == sorted(strings)
    for k in range(1, len(order)):
        assert lcps[k] == common_prefix(strings[order[k - 1]], strings[order[k]])


def brute(texts, length):
    seen = {}
    raws = [(t or "").encode() for t in texts]
    for raw in raws:
        for p in range(len(raw) - length + 1):
            seen[raw[p : p + length]] = seen.get(raw[p : p + length], 0) + 1
    out = []
    for raw in raws:
        gone = bytearray(len(raw))
        for p in range(len(raw) - length + 1):
            if seen[raw[p : p + length]] > 1:
                gone[p : p + length] = b"\1" * length
        kept = bytes(b for b, g in zip(raw, gone, strict=True) if not g)
        spans = sum(1 for i, g in enumerate(gone) if g and (i == 0 or not gone[i - 1]))
        out.append((len(raw), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("group_max", [20_000, 1])
def test_removal_against_brute_force(docs_of, group_max):
    rng = random.Random(5)
    blocks = ["".join(rng.choices("abcdé ", k=rng.randint(10, 90))) for _ in range(12)]
    texts = ["".join(rng.choices(blocks, k=rng.randint(1, 6))) for _ in range(60)] + ["", None, "x" * 300, "xy" * 70, blocks[0] * 3]
    params = SuffixDedupParams(length=40, gram=20, group_max=group_max)
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup(docs_of(enumerate(texts)), params).collect()}
    assert got == dict(enumerate(brute(texts, 40)))


def test_removal_of_nothing(docs_of):
    assert suffix_dedup(docs_of([])).collect() == []


def test_transducer(tmp_path):
    rng = random.Random(1)
    words = {bytes(rng.choices(b"abc", k=rng.randint(1, 8))): tuple(rng.choices(range(99), k=rng.randint(0, 3))) for _ in range(500)}
    path = tmp_path / "x.lexicon"
    path.write_bytes(compile_lexicon(words.items()))
    lexicon = Lexicon(str(path))
    assert all(lexicon.get(w) == out for w, out in words.items())
    assert lexicon.get(b"") is None and lexicon.get(b"zz") is None and lexicon.get(b"abcabcabcabc") is None
    assert lexicon.n_states < sum(map(len, words))


def test_encoder_against_the_library():
    import json

    tokenizers = pytest.importorskip("tokenizers")
    reference = tokenizers.Tokenizer.from_file(default_tokenizer())
    with open(default_tokenizer(), "rb") as f:
        mine = Encoder(Rules(json.load(f) | {"unknown_ranges": unknown_ranges()}))
    rng = random.Random(2)
    parts = ["<|endoftext|>", "<|startoftext|>", "'s", "'LL", "Σ", "İ", "é", " ", "\n", "\x1c", "\x85", "　", "1", "²", "_", "!!", "😀", "日本", "ß", "A", "th", "<|", "a" * 70, "ﬁ"]
    for _ in range(1500):
        text = "".join(rng.choices(parts, k=rng.randint(0, 10)))
        ids = reference.encode(text, add_special_tokens=False).ids
        got, back = mine.both(text)
        assert got == " ".join(map(str, ids))
        assert back == reference.decode(ids, skip_special_tokens=False)


def test_round_trip_on_spark(docs_of):
    docs = docs_of([(1, "The cat's hat"), (2, None), (3, ""), (3, "")])
    rows = {r["doc_id"]: r for r in encode(docs).collect()}
    assert rows[2]["n_tokens"] == 0 and rows[2]["ids_sha256"] == hashlib.sha256(b"").hexdigest()
    back = {r["doc_id"]: r["text"] for r in decode(encode(docs)).collect()}
    assert hashlib.sha256(back[1].encode()).hexdigest() == rows[1]["decoded_sha256"]
    assert encode(docs_of([])).count() == 0
