"""Cepstral audio descriptors: 25 ms windows every 10 ms, 13 coefficients with first and second differences, and energy."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

FILTERS, SMALLEST = 26, 1e-10


def mel_bank(n_filters: int, n_fft: int, rate: int) -> np.ndarray:
    """Triangular filters evenly spaced on the mel scale."""
    mel = np.linspace(0, 2595 * np.log10(1 + rate / 2 / 700), n_filters + 2)
    hz = 700 * (10 ** (mel / 2595) - 1)
    f = np.fft.rfftfreq(n_fft, 1 / rate)
    low, mid, high = hz[:-2, None], hz[1:-1, None], hz[2:, None]
    return np.maximum(0, np.minimum((f - low) / (mid - low), (high - f) / (high - mid)))


def frames_of(signal: np.ndarray, rate: int, win_ms: float, hop_ms: float) -> np.ndarray:
    win, hop = round(rate * win_ms / 1000), round(rate * hop_ms / 1000)
    if len(signal) < win:
        return np.zeros((0, win))
    return np.lib.stride_tricks.sliding_window_view(signal, win)[::hop]


def differences(x: np.ndarray) -> np.ndarray:
    """Central slope over two frames either side, edges repeated."""
    p = np.pad(x, ((2, 2), (0, 0)), mode="edge")
    return (p[3:-1] - p[1:-3] + 2 * (p[4:] - p[:-4])) / 10 if len(x) else x


def cepstral_matrix(signal: np.ndarray, rate: int = 16_000, win_ms: float = 25, hop_ms: float = 10, n_channels: int = 13) -> np.ndarray:
    """One row of 3 x n_channels + 1 values per window."""
    own = frames_of(np.asarray(signal, float), rate, win_ms, hop_ms)
    if not len(own):
        return np.zeros((0, 3 * n_channels + 1))
    n_fft = 1 << (own.shape[1] - 1).bit_length()
    power = np.abs(np.fft.rfft(own * np.hamming(own.shape[1]), n_fft)) ** 2 / n_fft
    bands = np.log(np.maximum(power @ mel_bank(FILTERS, n_fft, rate).T, SMALLEST))
    basis = np.cos(np.pi / FILTERS * np.outer(np.arange(1, n_channels + 1), np.arange(FILTERS) + 0.5))
    c = bands @ basis.T * np.sqrt(2 / FILTERS)
    d = differences(c)
    energy = np.log(np.maximum((own**2).sum(1), SMALLEST))
    return np.hstack([c, d, differences(d), energy[:, None]])


def cepstral(signals: DataFrame, rate: int = 16_000, win_ms: float = 25, hop_ms: float = 10, n_channels: int = 13) -> DataFrame:
    """item_id, frame, kind, vec from (item_id, signal array<float>). Signals stay in their Arrow batch; rows are independent."""

    def run(batches):
        for pdf in batches:
            rows = [(i, f, "audio", v) for i, s in zip(pdf["item_id"], pdf["signal"], strict=True) if s is not None for f, v in enumerate(cepstral_matrix(s, rate, win_ms, hop_ms, n_channels))]
            import pandas as pd

            yield pd.DataFrame(rows, columns=["item_id", "frame", "kind", "vec"])

    return signals.select("item_id", "signal").mapInPandas(run, "item_id long, frame int, kind string, vec array<double>")
