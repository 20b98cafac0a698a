"""Media columns: audio features.

Payloads are stored as mono 8-bit RIFF/WAVE bytes in a binary column. Features of a stored clip: polyphase
resampling by a rational factor (only the taps that meet a sample are multiplied), log-mel energies of overlapped
windowed frames, and speech-like segments from frame energy with hysteresis (a segment opens above ``high`` and
closes only below ``low``). Log-mel frames leave as fixed-shape tensors of ``frames x mels`` with the time span
each covers, as Arrow fixed-shape-tensor columns where asked for.

Work on a clip goes in blocks of ``BLOCK`` samples, so memory is bounded whatever its length, and each clip is
computed on its own, so equal clips have equal features.

Defined results: null text is an empty payload, padded to 64 zero bytes; the last frame of a clip is
zero-padded where samples run out; repeated rows get equal results; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelsort.llm.common import Stage

UNIT, RATE = 64, 16000
BLOCK = 720 * 360  # a multiple of the usual down factors


def payload(text: str | None) -> bytes:
    """UTF-8 bytes, zero-padded to a positive multiple of 64."""
    raw = (text or "").encode("utf-8")
    return raw + bytes(max(UNIT, -(-len(raw) // UNIT) * UNIT) - len(raw))


def to_wave(samples: bytes, rate: int = RATE) -> bytes:
    """Mono, 8-bit unsigned samples."""
    fmt = struct.pack("<4sIHHIIHH", b"fmt ", 16, 1, 1, rate, rate, 1, 8)
    body = b"WAVE" + fmt + struct.pack("<4sI", b"data", len(samples)) + samples + b"\0" * (len(samples) % 2)
    return struct.pack("<4sI", b"RIFF", len(body)) + body


def from_wave(data: bytes) -> tuple[int, bytes]:
    """Rate and samples of a mono 8-bit file; chunks it does not know are skipped."""
    if data[:4] != b"RIFF" or data[8:12] != b"WAVE":
        raise ValueError("not a RIFF/WAVE file")
    at, rate = 12, 0
    while at + 8 <= len(data):
        name, size = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
        if name == b"fmt ":
            code, channels, rate, _, _, bits = struct.unpack_from("<HHIIHH", data, at + 8)
            if (code, channels, bits) != (1, 1, 8):
                raise ValueError("only mono 8-bit samples")
        elif name == b"data":
            return rate, data[at + 8 : at + 8 + size]
        at += 8 + size + size % 2
    raise ValueError("no data chunk")


@lru_cache
def _phases(up: int, down: int, half: int) -> np.ndarray:
    """Windowed-sinc low-pass, one row of taps per phase."""
    width = max(up, down)
    n = np.arange(-half * width, half * width + 1)
    taps = np.sinc(n / width) / width * np.hamming(len(n)) * up
    per = -(-len(taps) // up)
    grid = np.zeros(per * up)
    grid[: len(taps)] = taps
    return np.ascontiguousarray(grid.reshape(per, up).T[:, ::-1], dtype=np.float32)


def resample(x: np.ndarray, up: int, down: int, half: int = 4) -> np.ndarray:
    """y[m] = sum_k x[k] h[m down - k up + delay]: every output takes the taps of its phase only."""
    bank = _phases(up, down, half)
    per, delay = bank.shape[1], half * max(up, down)
    n = -(-len(x) * up // down)
    y = np.empty(n, np.float32)
    padded = np.concatenate([np.zeros(per, np.float32), x.astype(np.float32), np.zeros(per + 1, np.float32)])
    views = np.lib.stride_tricks.sliding_window_view(padded, per)
    for r in range(min(up, n)):  # outputs r, r + up, ... share one phase; their inputs are `down` apart
        t = r * down + delay
        phase, first = t % up, t // up
        count = len(range(r, n, up))
        lo = first + 1  # window of inputs first-per+1 .. first, shifted by the left padding
        rows = views[lo : lo + (count - 1) * down + 1 : down]
        part = rows @ bank[phase]
        y[r::up][: len(part)] = part
        y[r::up][len(part) :] = 0
    return y


@lru_cache
def mel_bank(mels: int, size: int, rate: int) -> np.ndarray:
    """Triangular filters on the mel scale, bins x mels."""
    mel = lambda f: 2595 * np.log10(1 + f / 700)
    edges = 700 * (10 ** (np.linspace(mel(20.0), mel(rate / 2), mels + 2) / 2595) - 1)
    bins = np.fft.rfftfreq(size, 1 / rate)[:, None]
    rising = (bins - edges[:-2]) / (edges[1:-1] - edges[:-2])
    falling = (edges[2:] - bins) / (edges[2:] - edges[1:-1])
    return np.maximum(0, np.minimum(rising, falling)).astype(np.float32)


class Features:
    """Settings: target rate up/down times the stored one, frame and hop in samples there, mel bands, thresholds in dB."""

    def __init__(self, up: int = 1, down: int = 2, frame: int = 256, hop: int = 128, mels: int = 32, high: float = 3.0, low: float = -3.0, tensor_frames: int = 64):
        self.up, self.down, self.frame, self.hop, self.mels = up, down, frame, hop, mels
        self.high, self.low, self.tensor_frames = high, low, tensor_frames
        self.window = np.hanning(frame).astype(np.float32)

    def log_mel(self, samples: bytes, rate: int = RATE) -> tuple[np.ndarray, np.ndarray]:
        """Frames x mels natural-log energies, and frame energies in dB."""
        x = np.frombuffer(samples, np.uint8).astype(np.float32)
        x = (x - 128) / 128
        y = np.concatenate([self._block(x, i) for i in range(0, len(x), BLOCK)])
        steps = max(0, -(-(len(y) - self.frame) // self.hop))  # the last frame holds the last sample
        y = np.concatenate([y, np.zeros(self.frame + steps * self.hop - len(y), np.float32)])
        bank = mel_bank(self.mels, self.frame, rate * self.up // self.down)
        frames = np.lib.stride_tricks.sliding_window_view(y, self.frame)[:: self.hop]
        mel, energy = [], []
        for i in range(0, len(frames), 1024):
            f = frames[i : i + 1024] * self.window
            spec = np.fft.rfft(f)
            power = (spec.real**2 + spec.imag**2).astype(np.float32)
            mel.append(np.log(power @ bank + 1e-6))
            energy.append(10 * np.log10((f * f).mean(axis=1) + 1e-9))
        return np.concatenate(mel), np.concatenate(energy)

    def _block(self, x: np.ndarray, at: int) -> np.ndarray:
        """Outputs whose first input lies in the block; the filter also sees the samples around it."""
        around = self.down * 64
        lo, hi = max(0, at - around), min(len(x), at + BLOCK + around)
        y = resample(x[lo:hi], self.up, self.down)
        first = (at - lo) * self.up // self.down
        return y[first:] if hi == len(x) and at + BLOCK >= len(x) else y[first : first + BLOCK * self.up // self.down]

    def segments(self, energy: np.ndarray) -> list[tuple[int, int]]:
        """Frame spans [lo, hi): open above the mean by ``high`` dB, closed below it by ``low`` dB."""
        level = energy - energy.mean()
        # the state only changes at frames outside the band; between them the last such frame decides
        mark = np.where(level >= self.high, 1, np.where(level < self.low, -1, 0))
        at = np.maximum.accumulate(np.where(mark != 0, np.arange(len(mark)), -1))
        on = np.where(at >= 0, mark[at] == 1, False).astype(np.int8)
        edge = np.diff(np.concatenate([[0], on, [0]]))
        return list(zip(np.nonzero(edge == 1)[0].tolist(), np.nonzero(edge == -1)[0].tolist(), strict=True))

    def seconds(self, frame: int, rate: int = RATE) -> float:
        return frame * self.hop / (rate * self.up / self.down)


def feature_digest(mel: np.ndarray, spans: list[tuple[int, int]]) -> str:
    mean = ",".join(f"{v:.1f}" for v in mel.mean(axis=0) + 0.0)
    return f"frames={len(mel)};segments={len(spans)};active={sum(b - a for a, b in spans)};mel={mean}"


def stored_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, media: the text as a clip."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 64):
                part = b.slice(at, 64)
                texts = part.column("text").to_pylist()
                sizes, clips = [len((t or "").encode("utf-8")) for t in texts], [to_wave(payload(t)) for t in texts]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(clips, pa.binary())], ["doc_id", "n_bytes", "media"])

    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return texts.mapInArrow(run, "doc_id long, n_bytes long, media binary")


def described(stored: DataFrame, settings: dict | None = None) -> DataFrame:
    """What the stored clips (doc_id, n_bytes, media) hold: the columns of ``media_table``; null media gives no row."""
    options = dict(settings or {})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = Features(**options)
        span = pa.list_(pa.struct([("start_s", pa.float64()), ("end_s", pa.float64())]))
        for b in batches:
            for at in range(0, b.num_rows, 64):
                part = b.slice(at, 64)
                rows, blocks, times, first = [], [], [], [0]
                for doc, n_bytes, data in zip(*(part.column(k).to_pylist() for k in ("doc_id", "n_bytes", "media")), strict=True):
                    rate, back = from_wave(data)
                    mel, energy = f.log_mel(back, rate)
                    spans = f.segments(energy)
                    seconds = lambda k, mel=mel, rate=rate, back=back: len(back) / rate if k == len(mel) else f.seconds(k, rate)
                    for k in range(0, len(mel), f.tensor_frames):
                        n = min(f.tensor_frames, len(mel) - k)
                        times.append((seconds(k), seconds(k + n), n))
                        blocks.append(np.zeros((f.tensor_frames, f.mels), np.float32))
                        blocks[-1][:n] = mel[k : k + n]
                    first.append(len(blocks))
                    rows.append((doc, n_bytes, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(data), hashlib.sha256(data).hexdigest(), feature_digest(mel, spans), [{"start_s": seconds(a), "end_s": seconds(z)} for a, z in spans], data))
                cols = list(zip(*rows, strict=True))
                types = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), span, pa.binary()]
                cells = pa.ListArray.from_arrays(pa.array(np.arange(len(blocks) + 1, dtype=np.int32) * (f.tensor_frames * f.mels)), pa.array(np.concatenate(blocks).ravel()))
                starts, ends, counts = zip(*times, strict=True)
                windows = pa.StructArray.from_arrays([pa.array(starts, pa.float64()), pa.array(ends, pa.float64()), pa.array(counts, pa.int64()), cells], ["start_s", "end_s", "n_frames", "tensor"])
                yield pa.RecordBatch.from_arrays([*(pa.array(c, t) for c, t in zip(cols, types, strict=True)), pa.ListArray.from_arrays(pa.array(first, pa.int32()), windows)], list(_MEDIA))

    return stored.where("media is not null").select("doc_id", "n_bytes", "media").mapInArrow(run, ", ".join(f"{k} {v}" for k, v in _MEDIA.items()))


def media_table(docs: DataFrame, settings: dict | None = None, id_col: str = "doc_id", text_col: str = "text", keep_media: bool = True) -> DataFrame:
    """doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature, segments, media, tensors.

    The clips are written as a table; all else comes from what is read back. ``segments``: array of struct(start_s,
    end_s). ``media``: the stored bytes, null unless ``keep_media``. ``tensors``: array of struct(start_s, end_s,
    n_frames, tensor), log-mel windows of one fixed shape, zero-padded at the end; the last ends with the clip.
    """
    out = described(Stage(stored_media(docs, id_col, text_col), "media").df, settings)
    return out if keep_media else out.withColumn("media", F.lit(None).cast("binary"))


_MEDIA = {"doc_id": "long", "n_bytes": "long", "payload_bytes": "long", "payload_sha256": "string", "tail_crc32": "long", "media_bytes": "long", "media_sha256": "string", "feature": "string", "segments": "array<struct<start_s: double, end_s: double>>", "media": "binary", "tensors": "array<struct<start_s: double, end_s: double, n_frames: long, tensor: array<float>>>"}


def tensor_table(media: DataFrame, settings: dict | None = None, id_col: str = "doc_id", media_col: str = "media") -> DataFrame:
    """doc_id, part, start_s, end_s, n_frames, tensor: the ``tensors`` of stored clips, one a row."""
    stored = media.select(F.col(id_col).cast("long").alias("doc_id"), F.lit(None).cast("long").alias("n_bytes"), F.col(media_col).alias("media"))
    out = described(stored, settings).select("doc_id", F.posexplode("tensors").alias("part", "x"))
    return out.select("doc_id", F.col("part").cast("long").alias("part"), "x.start_s", "x.end_s", "x.n_frames", "x.tensor")


def as_tensor_column(table: pa.Table, shape: tuple[int, int] = (64, 32)) -> pa.Table:
    """An Arrow table with ``tensor`` as a fixed-shape-tensor extension column (what a training loader reads)."""
    flat = pa.concat_arrays([c.flatten() for c in table.column("tensor").chunks]) if table.num_rows else pa.array([], pa.float32())
    kind = pa.fixed_shape_tensor(pa.float32(), shape)
    cells = pa.FixedSizeListArray.from_arrays(flat.cast(pa.float32()), shape[0] * shape[1])
    at = table.schema.get_field_index("tensor")
    return table.set_column(at, pa.field("tensor", kind), pa.ExtensionArray.from_storage(kind, cells))
