"""Very long texts and pages: segments give what the whole would give, in bounded time and memory."""

import itertools
import random
import time

import numpy as np
import pyarrow as pa
import pytest

from trajkit.llm import common, curve_packing, mil_quality, mincut_extract, secret_scan, shingle_join, tokens_bpe, toxicity_grammar


def prose(n, seed=1):
    r = random.Random(seed)
    words = ["".join(r.choice("abcdefghij") for _ in range(r.randint(1, 9))) for _ in range(3000)] + ["you", "idiot.", "kill", "not"]
    return " ".join(r.choice(words) + r.choice(["", "", "", ",", ".", "\n"]) for _ in range(n))


def results(texts):
    model = toxicity_grammar.build([])
    return (
        curve_packing.curve_keys(texts), toxicity_grammar.evidence(texts, model), mil_quality.passages(texts), shingle_join.shingle_sets(texts)[0],
        np.concatenate(list(tokens_bpe.id_arrays()(texts[0].as_py()))),
    )


@pytest.mark.parametrize("text", [prose(20_000), prose(3_000) + " " + "x" * 150_000 + " " + prose(3_000, 2), "y" * 100_000, " \n" * 60_000, "é ü " * 30_000])
def test_segments_equal_the_whole(monkeypatch, text):
    whole = results(pa.array([text]))
    monkeypatch.setattr(common, "PIECE", 8_000)
    monkeypatch.setattr(tokens_bpe, "PART", 4_000)
    cut = results(pa.array([text]))
    assert (whole[0] == cut[0]).all() and np.allclose(whole[1][0], cut[1][0]) and whole[1][1] == cut[1][1]
    assert np.allclose(whole[2][0], cut[2][0]) and (whole[2][1] == cut[2][1]).all()
    assert (whole[3] == cut[3]).all() and (whole[4] == cut[4]).all()


def test_fifty_megabytes_of_text():
    text = prose(60_000) * 140
    texts, began = pa.array([text]), time.time()
    assert len(text) > 50_000_000
    assert curve_packing.curve_keys(texts).shape == (1,)
    assert toxicity_grammar.evidence(texts, toxicity_grammar.build([]))[0][0, 0] > 0
    assert len(mil_quality.passages(texts)[0]) > 80_000
    assert len(shingle_join.shingle_sets(texts)[0]) > 50_000
    assert len(secret_scan.base_spans(text)) == 0 == len(secret_scan.confirmed_spans(text))
    assert time.time() - began < 120
    for part in common.segments(texts):
        assert part.nbytes < 3 * common.PIECE


def test_words_of_any_length():
    texts = ["", " a b", None, "é" * 300 + " x", "q" * 5000 + " Z"] * 3
    w = common.Words(pa.array(texts), lower=True)
    found = [[bytes(w.data[w.start[i] : w.end[i]]).decode() for i in range(w.bounds[k], w.bounds[k + 1])] for k in range(len(texts))]
    assert found == [(t or "").replace("Z", "z").split() for t in texts]
    by_word = {}
    for word, h in zip(itertools.chain(*found), w.hashes().tolist()):
        assert by_word.setdefault(word, h) == h
    assert len(set(by_word.values())) == len(by_word) and int(common.hash_word("z")) == by_word["z"]


@pytest.mark.parametrize("block", ["<div>short line</div>", "<div>some text that goes on, {n}</p>", "<section><div>words, {n}</div></section>", "<div><a href=x>link {n}</a></div><div>text here, more of it. {n}</div>"])
def test_a_page_of_very_many_blocks(block):
    page, began = "<html><body>" + "".join(block.format(n=k) for k in range(50_000)) + "</body></html>", time.time()
    text = mincut_extract.main_text(page)
    assert text.count("\n") >= 49_000 and time.time() - began < 60


def test_marks_nest():
    body = "<p>A paragraph of some length, with commas and stops. It goes on for a while.</p>"
    keep = lambda html: mincut_extract.main_text(f"<html><body>{html}</body></html>") != ""
    assert keep(f'<div class="with-sidebar"><article>{body}</article></div>') and keep(f"<div>{body}</div>")
    assert not keep(f'<div class="sidebar"><div class="content">{body}</div></div>')
    assert not keep(f'<section id="comments"><article class="comment"><div class="body">{body}</div></article></section>')


def test_deeply_nested_keys_are_confirmed():
    inner = bytes([0x02, 0x01, 0x00]) + bytes([0x04, 0x10]) + bytes(range(16))
    for _ in range(40):
        n = len(inner)
        inner = bytes([0x30]) + (bytes([n]) if n < 128 else bytes([0x82, n >> 8, n & 255])) + inner
    assert secret_scan.tlv_depth(inner) == 41 and secret_scan.is_key_encoding(inner)
    assert secret_scan.tlv_depth(inner[:-1]) == 0
    deep = b""
    for _ in range(5000):
        n = len(deep)
        deep = bytes([0x30]) + (bytes([n]) if n < 128 else bytes([0x84]) + n.to_bytes(4, "big")) + deep
    assert secret_scan.tlv_depth(deep) == 5000


def test_filters_of_a_join_lose_no_pair():
    r = np.random.default_rng(4)
    for _ in range(400):
        n = int(r.integers(1, 700))
        x = np.unique(r.integers(0, 2**63, n).astype(np.uint64))
        keep = x[r.random(len(x)) < r.uniform(0.7, 1.0)]
        y = np.unique(np.concatenate([keep, r.integers(0, 2**63, int(r.integers(0, n // 4 + 1))).astype(np.uint64)]))
        if not len(y):
            continue
        common_tokens = len(np.intersect1d(x, y))
        apart = shingle_join.bits_apart(shingle_join.parity_sketch(x), shingle_join.parity_sketch(y))
        assert apart <= len(x) + len(y) - 2 * common_tokens
        if 100 * common_tokens >= 75 * (len(x) + len(y) - common_tokens):
            assert shingle_join.share_prefixes(shingle_join.order_prefixes(x), shingle_join.order_prefixes(y), len(x), len(y))
