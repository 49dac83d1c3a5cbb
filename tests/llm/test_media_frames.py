"""A payload of one block has a fingerprint of its own, in which each byte counts."""

import numpy as np

from graphblocks.llm import media


def prints(text):
    return media.fingerprint(media.spectral_peaks(np.frombuffer(media.text_payload(text), np.uint8)))


def test_short_texts_have_fingerprints():
    texts = [b"", b"one", b"a line of some words", b"another line of other words", b"x" * 300, b"y" * 576]
    found = [prints(t).tolist() for t in texts]
    assert all(found) and len({tuple(f) for f in found}) == len(texts)


def test_bytes_at_block_borders_count():
    r = np.random.default_rng(0)
    samples = r.integers(90, 123, 576 * 3).astype(np.uint8)
    base = media.spectral_peaks(samples)
    for at in (1, 575, 576, 1151, 1152, 576 * 3 - 2):
        other = samples.copy()
        other[at] = 255
        assert not np.array_equal(media.spectral_peaks(other), base), at
