"""Waveforms as arrays: trimming, levels, joining, noise. Column functions, with an Arrow twin for real sample rates.

``sonify`` makes a stand-in waveform from text, since no recordings are given: ten samples a letter at 150 a second, a
gain for each source and hash-chosen silence at both ends.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from langspan.functions.binding import let
from langspan.functions.text import SAMPLES_PER_CHAR, hash48

EMPTY = "array<float>"


def peak(signal: Column) -> Column:
    """Largest absolute amplitude; 0 of an empty signal."""
    return F.coalesce(F.array_max(F.transform(signal, F.abs)), F.lit(0).cast("float"))


def bounds(signal: Column, threshold: float, relative: bool = True) -> Column:
    """(first, last) index from 1 of the samples above the threshold (a share of the peak, or absolute); null if none is."""
    limit = peak(signal) * threshold if relative else F.lit(float(threshold))
    loud = let(limit, lambda least: F.filter(F.transform(signal, lambda x, i: F.when(F.abs(x) > least, i + 1)), lambda i: i.isNotNull()))
    return let(loud, lambda at: F.when(F.size(at) > 0, F.struct(F.element_at(at, 1).alias("first"), F.element_at(at, -1).alias("last"))))


def trim(signal: Column, threshold: float = 0.02, relative: bool = True, mode: str = "amplitude", frame: int = 15) -> Column:
    """Without leading and trailing silence: samples under the amplitude threshold, or frames under the energy threshold.

    A signal that is silent throughout becomes empty.
    """
    nothing = F.array().cast(EMPTY)
    if mode == "amplitude":
        return let(signal, lambda x: let(bounds(x, threshold, relative), lambda b: F.when(b.isNotNull(), F.slice(x, b["first"], b["last"] - b["first"] + 1)).otherwise(nothing)))

    def by_energy(x: Column) -> Column:
        count = F.greatest(F.ceil(F.size(x) / frame).cast("int") - 1, F.lit(0))
        frames = F.transform(F.sequence(F.lit(0), count), lambda k: energy(F.slice(x, k * frame + 1, F.lit(frame))))

        def cut(e: Column) -> Column:
            limit = F.array_max(e) * threshold if relative else F.lit(float(threshold))
            loud = let(limit, lambda least: F.filter(F.transform(e, lambda v, k: F.when(v > least, k)), lambda k: k.isNotNull()))
            return let(loud, lambda at: F.when(F.size(at) > 0, F.slice(x, F.element_at(at, 1) * frame + 1, (F.element_at(at, -1) - F.element_at(at, 1) + 1) * frame)).otherwise(nothing))

        return let(frames, cut)

    return let(signal, by_energy)


def energy(signal: Column) -> Column:
    """Mean square; 0 of an empty signal."""
    total = F.aggregate(signal, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    return F.when(F.size(signal) > 0, total / F.size(signal)).otherwise(0.0)


def rms(signal: Column) -> Column:
    return F.sqrt(energy(signal))


def peak_scale(signal: Column, scale: float = 1.0) -> Column:
    """Peak-normalised, then scaled; an all-zero signal stays as it is."""
    return let(signal, lambda s: let(peak(s), lambda top: F.when(top > 0, F.transform(s, lambda x: (x / top * scale).cast("float"))).otherwise(s)))


def silence(n: int) -> Column:
    return F.array_repeat(F.lit(0.0).cast("float"), n)


def noise(n: int, level: Column, seed: Column) -> Column:
    """Normal noise of a given root mean square, a function of the seed alone."""
    uniform = lambda i, salt: (F.pmod(F.xxhash64(seed, i, F.lit(salt)), F.lit(1 << 40)) + 0.5) / float(1 << 40)
    if n <= 0:
        return F.array().cast(EMPTY)
    return let(level, lambda r: F.transform(F.sequence(F.lit(1), F.lit(n)), lambda i: (F.sqrt(-2 * F.log(uniform(i, 1))) * F.cos(2 * 3.141592653589793 * uniform(i, 2)) * r).cast("float")))


def noise_level(signal_rms: Column, snr_db: float) -> Column:
    return signal_rms / 10 ** (snr_db / 20)


def join_signals(ordered: Column, begin: Column, gap: Column, end: Column) -> Column:
    """Signals in order between begin and end, with the gap between each two."""
    tail = F.flatten(F.transform(F.slice(ordered, 2, F.greatest(F.size(ordered) - 1, F.lit(0))), lambda s: F.concat(gap, s)))
    return F.concat(begin, F.coalesce(F.get(ordered, 0), F.array().cast(EMPTY)), tail, end)


def sonify(text: Column, source: Column, key: Column) -> Column:
    """The stand-in waveform of a text: a code of +-1 for each letter, the source's gain, silence of 0 to 75 samples at the ends."""
    gain = 0.1 + (hash48(F.concat(F.lit("gain:"), F.coalesce(source, F.lit("")))) % 1000) / 1000.0 * 0.8
    # the first sample of a letter is loud, so that no letter is taken for silence
    bit = lambda c, k: F.when(k == 0, 1.0).otherwise(1.0 - 2.0 * F.pmod(F.xxhash64(c, k), F.lit(2)))

    def made(g: Column) -> Column:
        body = F.flatten(F.transform(F.split(text, "(?<=.)(?=.)"), lambda c: F.transform(F.sequence(F.lit(0), F.lit(SAMPLES_PER_CHAR - 1)), lambda k: (bit(c, k) * g).cast("float"))))
        pad = lambda name: F.transform(F.sequence(F.lit(1), (hash48(F.concat(F.lit(name), key.cast("string"))) % 76 + 1).cast("int")), lambda i: (g * 0.01 * (1.0 - 2.0 * F.pmod(F.xxhash64(key, i, F.lit(name)), F.lit(2)))).cast("float"))
        return F.concat(pad("head:"), body, pad("tail:"))

    return let(gain, made)


def conditioned(signals: DataFrame, threshold: float, scale: float, batch: int = 64) -> DataFrame:
    """The Arrow twin of trim and peak_scale in one pass, for long waveforms; other columns pass through.

    ``signal`` is array<float>. Rows are worked in slices of ``batch``, since a second of speech is 64 KB here.
    """
    names = signals.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for k in range(0, whole.num_rows, batch):
                part = whole.slice(k, batch)
                out = []
                for signal in part.column("signal"):
                    x = np.asarray(signal.as_py() or [], np.float32)
                    loud = np.flatnonzero(np.abs(x) > np.float32(np.abs(x).max() * np.float32(threshold))) if len(x) else []
                    x = x[loud[0] : loud[-1] + 1] if len(loud) else x[:0]
                    out.append((x / np.abs(x).max() * np.float32(scale)).astype(np.float32) if len(x) else x)
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.list_(pa.float32())) if n == "signal" else part.column(n) for n in names], names)

    return signals.mapInArrow(run, signals.schema)
