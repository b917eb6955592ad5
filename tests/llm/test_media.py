"""Fingerprints cover every stored sample."""

import numpy as np
import pytest

media = pytest.importorskip("bundlery.llm.media_columns")


@pytest.mark.parametrize("n", [320, 448, 64 * 1001])
def test_the_last_samples_count(n):
    assert (n - media.FRAME) % media.HOP == 64
    a = np.random.default_rng(n).integers(32, 127, n, dtype=np.uint8)
    b = a.copy()
    b[-64:] = 128 + (100 * np.sin(np.arange(64) * 1.3)).astype(int)
    assert media.peak_pairs(a.tobytes()).tolist() != media.peak_pairs(b.tobytes()).tolist()


@pytest.mark.parametrize("n", [64, 256, 320, 384])
def test_padding_is_silence(n):
    a = np.random.default_rng(n).integers(32, 127, n, dtype=np.uint8).tobytes()
    whole = a + bytes([128]) * (max(256, -(-n // 128) * 128) - n)
    assert media.peak_pairs(a).tolist() == media.peak_pairs(whole).tolist() != []
