"""Kernels without Spark: tokens, packing schedule, Matroska, WARC, SimHash, KD-trees, label model."""

import hashlib

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from mergecount.llm import kdsearch, matroska, packing, simhash, tokens, toxicity, warc


@pytest.fixture(scope="module")
def tok():
    return tokens.WordTokenizer(packing.tokenizer_definition())


@pytest.mark.parametrize("text", ["", "  ", "It's don't 's 'S ’s", "İstanbul ΣΑΣ", "x²½ \x1c a\xa0b", "<|endoftext|> hi", "日本語 テスト", "é CAFÉ ß ẞ", "12ab3.5!?_x__y", "a­b ªº", "Word, word. (word)"])
def test_tokens_equal_the_tokenizer(tok, text):
    assert np.frombuffer(tok.encode(text), dtype=tok.dtype).tolist() == tok.tokenizer.encode(text, add_special_tokens=False).ids


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet=st.characters(max_codepoint=0x24F), max_size=40))
def test_tokens_equal_the_tokenizer_on_any_latin_text(tok, text):
    assert np.frombuffer(tok.encode(text), dtype=tok.dtype).tolist() == tok.tokenizer.encode(text, add_special_tokens=False).ids


@settings(max_examples=30, deadline=None)
@given(st.lists(st.integers(1, 3000), min_size=1, max_size=5), st.data())
def test_schedule_is_a_permutation_and_keeps_proportions(totals, data):
    weights = [float(data.draw(st.integers(1, 5))) for _ in totals]
    s = packing.Schedule(totals, weights, window=64, quantum=8)
    queue = np.concatenate([np.full(n, i) for i, n in enumerate(totals)])
    at = np.concatenate([np.arange(n) for n in totals])
    place, _ = s.place(queue, at)
    assert sorted(place.tolist()) == list(range(sum(totals)))
    for i in range(len(totals)):
        assert (np.diff(place[queue == i]) > 0).all()
    open_rounds = np.arange(s.rounds + 1)
    open_rounds = open_rounds[open_rounds * 64 <= s.earned[1]]  # while all queues are open
    served = s.served(open_rounds)
    fair = np.outer(open_rounds * 64, np.array(weights) / sum(weights))
    assert (np.abs(np.minimum(fair, totals) - served) <= 8 + 1e-6).all() or (served == np.array(totals)).any()


def test_pieces_cover_documents_and_fill_windows():
    totals = [5000, 900, 41]
    s = packing.Schedule(totals, [float(t) for t in totals], window=256, quantum=16)
    queue, begin, size = np.array([0, 0, 1, 2]), np.array([0, 4999, 0, 0]), np.array([4999, 1, 900, 41])
    pieces = [tuple(map(int, p)) for part in packing.cut_pieces(s, queue, begin, size) for p in zip(*part, strict=True)]
    windows: dict = {}
    for row, start, length, seq, offset in pieces:
        assert length > 0 and offset + length <= 256
        windows.setdefault(seq, []).append((offset, length))
    for row, n in enumerate(size):
        own = sorted((start, length) for r, start, length, _, _ in pieces if r == row)
        assert own[0][0] == 0 and sum(x for _, x in own) == n and all(a + b == c for (a, b), (c, _) in zip(own, own[1:], strict=False))
    for seq, spans in windows.items():
        spans.sort()
        assert spans[0][0] == 0 and all(a + b == c for (a, b), (c, _) in zip(spans, spans[1:], strict=False))
        assert sum(x for _, x in spans) == 256 or seq == max(windows)


@settings(max_examples=30, deadline=None)
@given(st.lists(st.binary(min_size=1, max_size=700), min_size=1, max_size=9), st.sampled_from(["xiph", "ebml"]), st.booleans())
def test_lacing_round_trip(frames, kind, group):
    kind = "none" if len(frames) == 1 else kind
    body = matroska.block(5, 7, frames, kind)
    block = matroska.element(matroska.BLOCK_GROUP, matroska.element(matroska.BLOCK, body)) if group else matroska.element(matroska.SIMPLE_BLOCK, body)
    data = matroska.element(matroska.EBML, b"") + matroska._id(matroska.SEGMENT) + b"\x01" + b"\xff" * 7 + matroska._id(matroska.CLUSTER) + b"\xff" + matroska._uint(matroska.CLUSTER_TIME, 3) + block
    found = matroska.parse(data, strict=True).packets
    assert [data[p.start : p.start + p.size] for p in found] == frames
    assert {(p.track, p.timestamp_ms, p.lacing, p.key) for p in found} == {(5, 10, kind, True)}


@pytest.mark.parametrize("n", [0, 1, 191, 192, 193, 192 * 64, 192 * 64 * 16 * 2 + 5])
def test_mux_round_trip(n):
    payload = matroska.padded(bytes(i % 251 for i in range(n)))
    assert len(payload) % 192 == 0 and len(payload) >= 192
    media = matroska.mux(payload)
    assert matroska.read_back(media) == payload
    parsed = matroska.parse(media, strict=True)
    assert [p.timestamp_ms for p in parsed.packets] == [24 * i for i in range(len(payload) // 192)]
    assert parsed.tracks[1]["codec"] == "A_PCM/INT/LIT" and parsed.tracks[1]["bits"] == 8
    assert [(t, place) for t, _, place in parsed.cues] == [(t, at) for at, t in parsed.clusters]
    cut = matroska.parse(media[: len(media) // 2])
    assert cut.packets == parsed.packets[: len(cut.packets)]
    with pytest.raises(ValueError):
        matroska.parse(media[: len(media) // 2], strict=True)


@settings(max_examples=40, deadline=None)
@given(st.binary(max_size=500), st.integers(1, 60))
def test_record_stream_in_any_pieces(payload, step):
    fields = {"WARC-Payload-Digest": "sha256:" + hashlib.sha256(payload).hexdigest()}
    data = warc.record_head("response", "urn:page:1", len(payload), fields) + payload + b"\r\n\r\n"
    s = warc.RecordStream()
    assert b"".join(s.feed(data[i : i + step]) for i in range(0, len(data), step)) == payload
    assert s.close()["WARC-Type"] == "response" and s.size == len(payload)


def test_bad_digest_raises():
    s = warc.RecordStream()
    s.feed(warc.record_head("response", "urn:page:1", 1, {"WARC-Payload-Digest": "sha256:00"}) + b"x\r\n\r\n")
    with pytest.raises(ValueError):
        s.close()


def literal_fingerprint(text):
    words = [w for w in "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").replace("\t", " ").replace("\n", " ").split(" ") if w]
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or ([" ".join(words)] if words else [])
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


@pytest.mark.parametrize("text", [None, "", " \n", "One", "one Two", "a b c", "É é E " * 5, "w " * 700])
def test_fingerprint(text):
    assert simhash.fingerprint(None if text is None else text.encode()) % 2**64 == literal_fingerprint(text)


def test_anchor_covering_misses_no_pair():
    """Values at distance 0 or 1 always share an anchor, and all anchors are code words within 2."""
    rng = np.random.default_rng(0)
    x = rng.integers(0, 1 << 31, 400)
    y = np.concatenate([x, x ^ (1 << rng.integers(0, 31, 400))])
    sets = lambda v: [set(a) for a in (lambda r, f: [f[r == i].tolist() for i in range(len(v))])(*simhash.anchors_of(v))]
    for a, b in zip(sets(np.concatenate([x, x])), sets(y), strict=True):
        assert a & b
    for value, anchors in zip(x[:50], sets(x[:50]), strict=True):
        assert len(anchors) in (1, 16) and all(bin(value ^ a).count("1") <= 2 for a in anchors)


def test_stars_connect_what_pairs_connect():
    rng = np.random.default_rng(3)
    fps = np.unique(np.array([0x0123456789ABCDEF ^ sum(1 << int(b) for b in rng.choice(40, rng.integers(0, 9), replace=False)) for _ in range(300)], dtype=np.int64))

    def groups(links):
        root = {int(f): int(f) for f in fps}

        def find(v):
            while root[v] != v:
                v = root[v]
            return v

        for a, b in links:
            a, b = find(int(a)), find(int(b))
            root[max(a, b)] = min(a, b)
        return {f: find(f) for f in root}

    pairs = [(a, b) for i, a in enumerate(fps) for b in fps[i + 1 :] if bin(int(a) ^ int(b)).count("1") <= 3]
    assert groups(simhash.stars(fps)) == groups(pairs)
    side = rng.integers(0, 2, len(fps))
    crossing = [(a, b) for i, a in enumerate(fps) for j, b in enumerate(fps) if i < j and side[i] != side[j] and bin(int(a) ^ int(b)).count("1") <= 3]
    assert groups(simhash.stars(fps, side)) == groups(crossing)


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 60), st.integers(1, 4), st.integers(0, 2**32))
def test_tree_search_is_exact(n, dims, seed):
    rng = np.random.default_rng(seed)
    v = rng.integers(-3, 4, (n, dims)) if seed % 2 else rng.integers(-2000, 2000, (n, dims))
    ids = rng.permutation(n * 2)[:n]
    q = np.arange(0, n, 3)
    best = kdsearch.Best(np.full(len(q), kdsearch.LEAST), np.full(len(q), kdsearch.LAST), 4)
    half = n // 2  # two trees, one after the other
    for own in (slice(0, half), slice(half, n)):
        if n and len(ids[own]):
            kdsearch.search(kdsearch.build(ids[own], v[own], leaf=8), ids[q], v[q], best)
    for i, j in enumerate(q):
        scores = v @ v[j]
        expected = sorted(((-int(s), int(x)) for s, x in zip(scores, ids, strict=True) if x != ids[j]))[:4]
        got = [(-int(s), int(x)) for s, x in zip(best.scores[i], best.ids[i], strict=True) if s > kdsearch.LEAST]
        assert got == expected
