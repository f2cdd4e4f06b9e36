"""Parts of the operators that need no Spark, against brute force."""

import random
import re

import numpy as np
import pytest

from overlapgraph.llm import audio, bpe, crf, html_main, langid, licenses, probminhash, quality
from overlapgraph.llm import textvec as tv
from overlapgraph.llm.queries import bpe_path


def test_word_hashes_do_not_depend_on_place():
    block = tv.Block(["one two one", "", "two"])
    h = block.word_hashes()
    assert h[0] == h[2] and h[1] == h[3] and h[0] != h[1]
    assert block.w_doc.tolist() == [0, 0, 0, 2]


def test_blocks_cover_every_text_once():
    texts = ["a" * n for n in (5, 50, 3, 1, 200, 0, 7)]
    got = [i for a, b in tv.blocks(texts, 60) for i in range(a, b)]
    assert got == list(range(len(texts))) and list(tv.blocks([], 60)) == []


def brute_shingles(text):
    w = [x for x in re.split(r"[\x20\x09-\x0D]+", text.lower()) if x]
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def test_shingles_and_jaccard_against_brute_force():
    rng = random.Random(1)
    texts = [" ".join(rng.choice("abcdef") for _ in range(n)) for n in (0, 1, 4, 5, 6, 40, 41)] + ["A b\tc\n d e f", "a b c d e f"]
    doc, h, count = probminhash.shingle_sets(texts)
    for i, a in enumerate(texts):
        assert (doc == i).sum() == len(brute_shingles(a))
        for j, b in enumerate(texts):
            sa, sb = brute_shingles(a), brute_shingles(b)
            want = len(sa & sb) / max(len(sa | sb), 1)
            # with equal weights the similarity is that of the sets
            one = [(h[doc == z], np.ones((doc == z).sum())) for z in (i, j)]
            assert probminhash.similarity_of(*one) == pytest.approx(want)


def test_similarity_of_weighted_sets_against_its_definition():
    rng = random.Random(3)
    for _ in range(60):
        a = {i: rng.choice([1.0, 1.0, 2.0, 5.5]) for i in rng.sample(range(40), rng.randint(1, 30))}
        b = {i: a.get(i, 1.0) if rng.random() < 0.6 else rng.choice([1.0, 3.0]) for i in rng.sample(range(40), rng.randint(1, 30))}
        packed = [(np.array(sorted(x), np.uint64), np.array([x[k] for k in sorted(x)])) for x in (a, b)]
        want = probminhash.probability_jaccard(a, b)
        assert probminhash.similarity_of(*packed) == pytest.approx(want)
        share = [sum(x[k] for k in a.keys() & b.keys()) / sum(x.values()) for x in (a, b)]
        # the bound that the exact join rests on
        assert not want or 1 / want >= 1 / share[0] + 1 / share[1] - 1 - 1e-9


def test_registers_estimate_probability_jaccard():
    rng = random.Random(2)
    k, errors = 512, []
    for _ in range(8):
        a = {i: rng.choice([1, 1, 2, 5]) for i in range(60)}
        b = {i: (w if rng.random() < 0.8 else w + 1) for i, w in a.items() if rng.random() < 0.9} | {1000 + i: 1 for i in range(6)}
        rows = [(d, e, w) for d, s in enumerate((a, b)) for e, w in s.items()]
        doc, el, w = (np.array(c) for c in zip(*rows))
        sig = probminhash.signatures(doc, tv.mix(el.astype(np.uint64)), w.astype(float), 2, k)
        errors.append((sig[0] == sig[1]).mean() - probminhash.probability_jaccard(a, b))
    assert abs(np.mean(errors)) < 0.03 and max(map(abs, errors)) < 0.1


def test_bpe_learns_the_new_pieces_of_a_text_in_one_pass():
    """One start of the automaton a text, and narrower patterns that cut as the whole one does."""
    coder = bpe.PrefixEncoder(bpe.read_spec(bpe_path()))
    texts = ["zqxj vwkp 8371 it's", "h\u00e9ll\u00f6 \u4e2d\u6587 \u0663\u0664\u2028x", "a\U0001d400b \U00020000\U0001f600 \U0001d7d8", "\x85\xa0 \t'll  ", ""]
    want = [[i for p in coder.pattern.findall(t) for i in coder.piece(p.encode())] for t in texts]
    starts, real = [], coder.automaton

    class Counted:
        def iter(self, joined):
            starts.append(joined)
            return real.iter(joined)

    coder.automaton = Counted()
    assert [coder.encode(t) for t in texts] == want and len(starts) == 4
    assert [coder.encode(t) for t in texts] == want and len(starts) == 4
    assert len(coder.ascii.pattern) < len(coder.plain.pattern) < len(coder.pattern.pattern)


def test_bpe_equals_the_tokenizers_library():
    from tokenizers import Tokenizer

    path = bpe_path()
    ours, theirs = bpe.PrefixEncoder(bpe.read_spec(path)), Tokenizer.from_file(path)
    rng = random.Random(3)
    bits = ["a", "b", " ", "  ", "\n", "'s", "’", "é", "日本", "1", "٣", "½", "<|endoftext|>", "\x85", "😀", "\t", "ing", "tion", "-", "é", " the", "​"]
    texts = ["", "aaaa", "aaaaaaa", " " * 50, "é" * 999, "x" * 5000] + ["".join(rng.choice(bits) for _ in range(rng.randint(0, 60))) for _ in range(1500)]
    for t in texts:
        want = theirs.encode(t, add_special_tokens=False).ids
        assert ours.encode(t) == want
        assert ours.decode(want) == theirs.decode(want, skip_special_tokens=False) == t


def test_posteriors_of_long_chains_are_exact():
    rng = np.random.default_rng(0)
    for k in (1, 2, 4):
        emit, doc, trans = rng.normal(size=(700, k)) * 3, np.sort(rng.integers(0, 9, 700)), rng.normal(size=(k, k))
        psi = np.exp(emit - emit.max(axis=1, keepdims=True))
        f, b = langid._plain_passes(psi, doc, np.exp(trans))
        want = f * b / (f * b).sum(axis=1, keepdims=True)
        assert np.abs(langid.posteriors(emit, doc, trans) - want).max() < 1e-12


def test_code_switched_words_are_labelled():
    en, fr = "the river and the stone of that house was there", "le fleuve et la pierre de cette maison dans les rues"
    model = langid.train([en] * 8 + [fr] * 8, ["en"] * 8 + ["fr"] * 8, epochs=8)
    got = langid.label_words(en + " " + fr, model)
    assert [x[1] for x in got] == ["en"] * len(en.split()) + ["fr"] * len(fr.split())
    alone = [langid.predict_texts([t], model)[1][0] for t in (en, fr)]
    names, scores, switches = langid.predict_texts([en, fr, "", "123 !?"], model)
    assert np.allclose(scores[:2], alone)
    assert names == ["en", "fr", "und", "und"] and scores[2] == scores[3] == 0 and switches[0] == 0


def test_viterbi_against_all_paths():
    from itertools import product

    rng = random.Random(4)
    model = crf.ChainModel({f"f{i}": (rng.gauss(0, 1), rng.gauss(0, 1)) for i in range(6)}, [[0.3, -0.4], [-0.2, 0.5]])
    for _ in range(20):
        seq = [[f"f{rng.randrange(7)}" for _ in range(3)] for _ in range(6)]
        value = lambda path: sum(model.weights.get(f, (0, 0))[c] for pos, c in zip(seq, path) for f in pos) + sum(model.transitions[a][b] for a, b in zip(path, path[1:]))  # noqa: B023
        assert value(crf.viterbi(seq, model)) == pytest.approx(max(map(value, product((0, 1), repeat=6))))
    assert crf.viterbi([], model) == []


def test_page_text():
    model = html_main.train(600)
    rng = random.Random(77)
    right = total = 0
    for _ in range(120):
        page, labels = html_main.labelled_page(rng)
        blocks = html_main.leaf_blocks(page)
        assert len(blocks) == len(labels)
        got = crf.viterbi(html_main.block_features(blocks), model)
        right += sum(a == b for a, b in zip(got, labels))
        total += len(labels)
    assert right / total > 0.98
    page = (
        "<html><head><title>T</title><script>var a='</p>'</script></head><body><nav><ul><li><a href=/x>Home</a></li></ul></nav><div class='ad'>Buy now.</div>"
        "<article><h1>Head &amp; tail</h1><p>One\n two<b>three</b><br>four.<p>Caf&eacute; &#8364;5.</p></article><footer>&copy; site</footer></body></html>"
    )
    assert html_main.main_text(page, model) == "Head & tail One twothree four. Café €5."
    for odd in ("", "<", "<p", "</p></div>", "<!-- x", "<script>", "<p>" * 500, "<div class='", "text only &am"):
        html_main.main_text(odd, model)


def test_quality_scores_do_not_depend_on_the_batch():
    good, bad = "the river ran past the old stone house in winter", "BUY!! NOW!! CHEAP!! OFFER!! CLICK!!"
    model = quality.train([good, bad] * 20, [1, 0] * 20, buckets=1 << 12)
    texts = [good, bad, "", " \n", "x" * 10_000] * 3
    together = quality.score(texts, model.projected, model.offset)
    alone = [quality.score([t], model.projected, model.offset)[0] for t in texts]
    assert np.allclose(together, alone) and together[0] > 0.5 > together[1]


def test_quality_features_against_loops():
    text = "ab abc  ab ab"
    got = sorted(int(b) for _, ids in quality.features(tv.Block([text]), 1 << 18) for b in ids)
    grams = []
    padded = " " + text + " "
    for n in quality.NGRAMS:
        for i in range(len(padded) - n + 1):
            g = padded[i : i + n]
            if not (g[0] == " " and g[-1] == " ") and " " not in g[1:-1]:
                grams.append(g)
    words = text.split()
    assert len(got) == len(grams) + len(words) + len(words) - 1 + 1


def test_audio_round_trip_and_resampling():
    p = audio.AudioParams()
    for text in ("", "a", "é" * 31, "x" * 64, "word " * 5000):
        payload, n = audio.as_payload(text)
        assert len(payload) % 64 == 0 and len(payload) > 0 and payload[:n] == text.encode()
        raw, rate = audio.read_wav(audio.wav_bytes(payload, p.rate))
        assert raw == payload and rate == p.rate
        found = audio.analyse(audio.wav_bytes(payload, p.rate), p)
        for s, e, frames, t in audio.tensors(found):
            assert e > s and 0 < frames <= p.tensor_frames and t.shape == (p.tensor_frames, p.mels)
    x = np.sin(2 * np.pi * 440 * np.arange(16000) / 16000)
    y = audio.resample(x, 3, 5, 12)
    brute = np.zeros(len(y))
    h = audio._phases(3, 5, 12)
    padded = np.concatenate([np.zeros(11), x, np.zeros(20)])
    for m in range(len(y)):
        start, phase = divmod(m * 5, 3)
        brute[m] = padded[start + 6 : start + 18] @ h[phase][::-1]
    assert len(y) == 9600 and np.abs(y - brute).max() < 1e-4
    assert np.abs(y[100:-100] - np.sin(2 * np.pi * 440 * np.arange(9600) / 9600)[100:-100]).max() < 0.05


def test_segments_have_hysteresis():
    p = audio.AudioParams(min_frames=1, floor_quantile=0.0)
    energy = np.array([0, 0, 7, 4, 4, 2, 4, 7, 0], float)
    assert audio.segments(energy, p) == [(2, 5), (7, 8)]


def plain_audio(samples: bytes, p):
    """Resampling by inserting zeros, frames one by one, sums of squares by a plain Fourier sum."""
    x = (np.frombuffer(samples, np.uint8).astype(float) - 128) / 128
    n = np.arange(p.up * p.taps) - (p.up * p.taps - 1) / 2
    h = np.sinc(n / p.down) / p.down * np.hamming(len(n)) * p.up
    wide = np.zeros(len(x) * p.up)
    wide[:: p.up] = x
    full = np.concatenate([np.convolve(wide, h), np.zeros(p.up * p.down + len(h))])
    # the filter's delay: half its taps of a phase
    y = full[p.up * (p.taps // 2) :][:: p.down][: -(-len(x) * p.up // p.down)]
    if len(y) < p.window:
        y = np.concatenate([y, np.zeros(p.window - len(y))])
    wave = np.exp(-2j * np.pi * np.outer(np.arange(p.fft // 2 + 1), np.arange(p.window)) / p.fft)
    mel, energy = [], []
    bank = audio._mel_bank(p.mels, p.fft, p.out_rate)
    for a in range(0, len(y) - p.window + 1, p.hop):
        frame = y[a : a + p.window]
        mel.append(10 * np.log10(bank @ np.abs(wave @ (frame * np.hanning(p.window))) ** 2 + 1e-6))
        energy.append(10 * np.log10((frame**2).sum() / p.window + 1e-9))
    return np.array(mel), np.array(energy)


def test_stored_tensors_against_a_plain_path():
    p = audio.AudioParams()
    rng = random.Random(12)
    for text in ("", "short", "a" * 4000 + " " * 4000 + "ZZZ~~~" * 900, " ".join(rng.choice(["river", "STONE", "~~~", "   "]) for _ in range(6000))):
        payload, _ = audio.as_payload(text)
        found = audio.analyse(audio.wav_bytes(payload, p.rate), p)
        mel, energy = plain_audio(payload, p)
        assert mel.shape == found["mel"].shape and np.abs(mel - found["mel"]).max() < 0.05
        stored = audio.store_tensors(found)
        table = audio.load_tensors(stored)
        assert table.schema.field("values").type.shape == [p.tensor_frames, p.mels]
        at = 0
        for a, b in found["segments"]:
            assert (energy[a:b] >= np.quantile(energy, p.floor_quantile) + p.close_db - 0.1).all()
            for c in range(a, b, p.tensor_frames):
                used = min(p.tensor_frames, b - c)
                t = table["values"].combine_chunks().to_numpy_ndarray()[at]
                assert table["frames"][at].as_py() == used and np.abs(t[:used] - mel[c : c + used]).max() < 0.05 and not t[used:].any()
                assert table["start_s"][at].as_py() == pytest.approx(c * p.hop / p.out_rate) and table["end_s"][at].as_py() == pytest.approx(((c + used - 1) * p.hop + p.window) / p.out_rate)
                at += 1
        assert at == len(table) and audio.feature_text(found, stored).endswith("tensors=0" if not at else f"to_s={table['end_s'][-1].as_py():.4f}")


def test_anchor_words_lose_no_template_match():
    words = set(licenses.anchors())
    for _, text in licenses.TEMPLATES:
        grams = licenses.bigrams(licenses.normal_words(text))
        need = -(-len(grams) * 2 // 3)
        held = [g for g in grams if g.split(" ")[0] in words]
        assert len(grams) - len(held) < need
