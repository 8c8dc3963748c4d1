"""Augmentation of training segments, its controls and its exclusions.

What array expressions can state stays in the JVM; what needs a transform runs in numpy over Arrow batches.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _fold(v: Column) -> Column:
    return F.aggregate(v, F.lit(0.0), lambda s, x: s + x)


def znorm(x: Column) -> Column:
    """Zero mean, unit population deviation; a constant array becomes zeros."""
    n = F.size(x)
    centred = F.transform(F.array(_fold(x) / n), lambda m: F.transform(x, lambda v: v - m))[0]
    scaled = F.transform(F.array(centred), lambda c: F.transform(F.array(F.sqrt(_fold(F.transform(c, lambda v: v * v)) / n)), lambda sd: F.transform(c, lambda v: F.when(sd > 1e-12, v / sd).otherwise(0.0)))[0])
    return scaled[0]


def roll(x: Column, k: int) -> Column:
    """Circular shift to the right by k samples."""
    cut = F.size(x) - F.pmod(F.lit(k), F.size(x))
    return F.concat(F.slice(x, cut + 1, F.size(x) - cut), F.slice(x, F.lit(1), cut))


def mask_with_ambient(x: Column, noise: Column, start: int, length: int) -> Column:
    """A stretch overwritten by noise, never by zeros, whose edges would be a feature."""
    return F.transform(x, lambda v, i: F.when((i >= start) & (i < start + length), F.get(noise, F.pmod(i, F.size(noise)))).otherwise(v))


def mix_ambient(x: Column, noise: Column, snr_db: float) -> Column:
    """x plus noise scaled to the given ratio of powers; silent noise adds nothing."""
    power = lambda v: _fold(F.transform(v, lambda a: a * a))
    scale = F.sqrt(power(x) / F.nullif(power(noise), F.lit(0.0)) / F.lit(10.0 ** (snr_db / 10)))
    return F.transform(F.array(F.coalesce(scale, F.lit(0.0))), lambda k: F.zip_with(x, noise, lambda a, b: a + k * b))[0]


def multipath(x: Column, taps: list[tuple[int, float]]) -> Column:
    """Direct path plus delayed reflections (delay, gain); surface bounces have a negative gain."""
    return F.transform(x, lambda v, i: sum((F.when(i >= d, F.get(x, i - d)).otherwise(0.0) * g for d, g in taps), v))


def gain(x: Column, g: float) -> Column:
    """Left out of the recipe, as standardising undoes it."""
    return F.transform(x, lambda v: v * g)


def tilt(x: np.ndarray, db: float, rate: float, low_cap_db: float = 3.0) -> np.ndarray:
    """Slope of db over the band in the spectrum; what it takes from low frequencies is capped."""
    f = np.fft.rfft(x)
    at = np.linspace(-0.5, 0.5, len(f)) * db
    return np.fft.irfft(f * 10 ** (np.maximum(at, -low_cap_db) / 20), len(x))


def warp(x: np.ndarray, ratio: float) -> np.ndarray:
    """Negative control: resampling moves every line, which the peak check must see."""
    return np.interp(np.arange(len(x)) * ratio % len(x), np.arange(len(x)), x)


def phase_scramble(x: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """Negative control: the spectrum stays, the waveform does not."""
    f = np.fft.rfft(x)
    turn = np.exp(2j * np.pi * rng.random(len(f)))
    turn[0] = turn[-1] = 1
    return np.fft.irfft(f * turn, len(x))


def _copy(x: np.ndarray, noise: np.ndarray, rng: np.random.Generator, rate: float) -> tuple[np.ndarray, list[str]]:
    names = ["tilt", "mix", "multipath", "roll", "mask"]
    picked = sorted(rng.choice(5, rng.integers(2, 6), replace=False))
    n = len(x)
    level = np.sqrt((x**2).mean() / max((noise**2).mean(), 1e-12))
    for i in picked:
        if i == 0:
            x = tilt(x, rng.uniform(-4, 4), rate)
        elif i == 1:
            x = x + noise * level * 10 ** (-rng.uniform(10, 20) / 20)
        elif i == 2:
            gains = rng.uniform(0.05, 0.25, 3) * rng.choice([-1, 1], 3)
            gains *= min(1.0, 0.5 / np.linalg.norm(gains))
            x = x + sum(g * np.concatenate([np.zeros(d), x[: n - d]]) for d, g in zip(rng.integers(1, max(2, n // 8), 3), gains, strict=True))
        elif i == 3:
            x = np.roll(x, rng.integers(n))
        else:
            a, m = rng.integers(n), max(1, n // 16)
            x = np.where((np.arange(n) >= a) & (np.arange(n) < a + m), noise * level * 0.1, x)
    return x, [names[i] for i in picked]


def augment(segments: DataFrame, noise: np.ndarray, copies: int = 3, rate: float = 8000.0) -> DataFrame:
    """recording_id, start, copy (0 is the original), ops, x, peak_before, peak_after (bins), peak_kept.

    Draws depend on recording, start and copy alone. noise: (m, n) bank of quiet stretches, a fixed number of them.
    """
    held = segments.sparkSession.sparkContext.broadcast(noise)

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            rows = []
            for r, s, x in zip(part["recording_id"], part["start"], part["x"], strict=True):
                x = np.asarray(x, float)
                before = int(np.abs(np.fft.rfft(x - x.mean()))[1:].argmax()) + 1
                rows.append((r, s, 0, [], x, before, before, True))
                for c in range(1, copies + 1):
                    rng = np.random.default_rng([abs(int(r)), int(s), c])
                    y, ops = _copy(x - x.mean(), held.value[rng.integers(len(held.value))][: len(x)], rng, rate)
                    after = int(np.abs(np.fft.rfft(y))[1:].argmax()) + 1
                    rows.append((r, s, c, ops, y, before, after, abs(after - before) <= 1))
            yield pd.DataFrame(rows, columns=["recording_id", "start", "copy", "ops", "x", "peak_before", "peak_after", "peak_kept"])

    return segments.select("recording_id", "start", "x").mapInPandas(run, "recording_id long, start long, copy long, ops array<string>, x array<double>, peak_before long, peak_after long, peak_kept boolean")


def train_only(augmented: DataFrame, manifest: DataFrame) -> DataFrame:
    """The copies, or an error as soon as one belongs to a hull that the manifest does not put in training."""
    part = manifest.select("hull_id", "part")
    bad = F.coalesce(F.col("part"), F.lit("none")) != "train"
    checked = augmented.join(part, "hull_id", "left").withColumn("part", F.when(bad, F.raise_error(F.lit("a copy of a hull outside training"))).otherwise(F.col("part")))
    return checked.where("part = 'train'").drop("part")
