"""Media columns: audio stored without loss, and features of it as fixed-shape tensors with time spans.

A payload becomes a WAV file of unsigned 8-bit samples. Features are taken from the stored bytes: the samples are resampled by
2/3 with a polyphase filter (two sub-filters of a windowed sinc, one per output phase), cut into
half-overlapping frames, and each frame gives the logs of mel-spaced filterbanks of its power spectrum. Frames
whose energy rises over an upper bound start a segment that lasts until it falls under a lower one (hysteresis);
the bounds are set by the file's own mean and spread. Features go into tensors of TILE frames by BANDS bands, the last one
filled up with zeros, each with its time span.

Files are read in blocks of frames, so that memory does not grow with a file's length beyond the file itself. All
arithmetic is on one file at a time: equal payloads have equal features.

Cases: null text is empty text and gives one payload of spaces; repeated rows each get a row; an empty table
gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import functools
import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from commlens.llm.common import column_bytes, map_batches

RATE = 12_000
UP, DOWN = 2, 3
FRAME, HOP, BANDS, TILE = 256, 128, 20, 64
#: Bytes of payload per hop; payloads are whole multiples.
UNIT = HOP * DOWN // UP
TAPS = 12
BLOCK = 2048
_HEAD = struct.Struct("<4sI4s4sIHHIIHH4sI")
TENSOR = pa.fixed_shape_tensor(pa.float32(), (TILE, BANDS))


def payload_of(raw: bytes) -> bytes:
    """The bytes filled up with spaces to a positive multiple of UNIT."""
    return raw.ljust(max(1, -(-len(raw) // UNIT)) * UNIT, b" ")


def to_wav(payload: bytes, rate: int = RATE) -> bytes:
    n = len(payload)
    return _HEAD.pack(b"RIFF", 36 + n + n % 2, b"WAVE", b"fmt ", 16, 1, 1, rate, rate, 1, 8, b"data", n) + payload + b"\0" * (n % 2)


def read_wav(media: bytes) -> tuple[int, bytes]:
    """Rate and samples of an 8-bit file, found by its chunks."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a WAV file")
    at, rate = 12, 0
    while at + 8 <= len(media):
        name, size = struct.unpack_from("<4sI", media, at)
        if name == b"fmt ":
            kind, channels, rate, _, _, bits = struct.unpack_from("<HHIIHH", media, at + 8)
            if (kind, channels, bits) != (1, 1, 8):
                raise ValueError("not unsigned 8-bit samples of one channel")
        elif name == b"data":
            return rate, media[at + 8 : at + 8 + size]
        at += 8 + size + size % 2
    raise ValueError("no samples")


@functools.lru_cache(maxsize=1)
def sub_filters() -> np.ndarray:
    """(TAPS, UP): a windowed-sinc low pass at the lower of both Nyquist rates, dealt out by output phase. Output
    UP * m + q is the sum over taps of sub-filter q and the inputs around DOWN * m + q * DOWN / UP."""
    offset = np.arange(TAPS)[:, None] - (TAPS // 2 - 1) - np.arange(UP)[None, :] * DOWN / UP
    cut = UP / DOWN
    h = cut * np.sinc(cut * offset) * (0.5 + 0.5 * np.cos(np.pi * np.clip(offset / (TAPS / 2 + 1), -1, 1)))
    return h / h.sum(axis=0)


@functools.lru_cache(maxsize=1)
def mel_banks() -> np.ndarray:
    """(FRAME // 2 + 1, BANDS) triangles, evenly spaced on the mel scale."""
    rate = RATE * UP / DOWN
    mel = np.linspace(0, 2595 * np.log10(1 + rate / 2 / 700), BANDS + 2)
    edge = 700 * (10 ** (mel / 2595) - 1)
    f = np.arange(FRAME // 2 + 1)[:, None] * rate / FRAME
    return np.clip(np.minimum((f - edge[:-2]) / (edge[1:-1] - edge[:-2]), (edge[2:] - f) / (edge[2:] - edge[1:-1])), 0, None)


def log_mels(samples: bytes) -> np.ndarray:
    """(frames, BANDS): a frame per HOP resampled samples, centred there; outside the file there is silence."""
    raw = np.frombuffer(samples, dtype=np.uint8)
    frames = len(raw) // UNIT
    window = np.hanning(FRAME + 1)[:-1]
    out = np.empty((frames, BANDS))
    reach = TAPS + DOWN
    for first in range(0, frames, BLOCK):
        n = min(BLOCK, frames - first)
        a, b = (first - 1) * UNIT, (first + n) * UNIT
        x = np.zeros(b - a + 2 * reach)
        lo, hi = max(0, a - reach), min(len(raw), b + reach)
        x[lo - a + reach : hi - a + reach] = (raw[lo:hi].astype(float) - 128.0) / 128.0
        start = reach - (TAPS // 2 - 1)
        view = np.lib.stride_tricks.sliding_window_view(x, TAPS)[start : start + b - a : DOWN]
        y = (view @ sub_filters()).ravel()
        if first == 0:
            y[: HOP] = 0.0
        cut = np.lib.stride_tricks.sliding_window_view(y, FRAME)[::HOP][:n]
        power = np.abs(np.fft.rfft(cut * window, axis=1)) ** 2
        out[first : first + n] = np.log(power @ mel_banks() + 1e-6)
    return out


def segments(mels: np.ndarray, rise: float = 0.5, fall: float = 0.0) -> np.ndarray:
    """(segments, 2): first frame and frame after the last. A segment starts over mean + rise * spread of the frames' energies and
    ends under mean - fall * spread."""
    energy = mels.mean(axis=1)
    mean, spread = energy.mean(), energy.std()
    mark = np.where(energy > mean + rise * spread + 1e-9, 1, np.where(energy < mean - fall * spread - 1e-9, -1, 0))
    at = np.maximum.accumulate(np.where(mark != 0, np.arange(len(mark)), -1))
    on = (at >= 0) & (mark[at] > 0)
    turn = np.diff(np.concatenate([[0], on.astype(np.int8), [0]]))
    return np.stack([np.flatnonzero(turn == 1), np.flatnonzero(turn == -1)], axis=1)


def tiles(mels: np.ndarray) -> pa.FixedShapeTensorArray:
    """Features as an Arrow array of TILE x BANDS tensors."""
    n = -(-len(mels) // TILE)
    full = np.zeros((n * TILE, BANDS), dtype=np.float32)
    full[: len(mels)] = np.round(mels, 2)
    return pa.ExtensionArray.from_storage(TENSOR, pa.FixedSizeListArray.from_arrays(pa.array(full.ravel()), TILE * BANDS))


def feature_tiles(media: DataFrame) -> DataFrame:
    """From (doc_id, media): (doc_id, tile, start_ms, end_ms, n_frames, active_ms, values) per tensor, ``values`` being TILE * BANDS numbers by rows;
    ``as_tensors`` gives the Arrow tensors of a batch. active_ms is the time of the tile within segments."""
    step = 1000 * HOP * DOWN / UP / RATE

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for key, raw in zip(batch.column("doc_id"), batch.column("media"), strict=True):
                if not raw.is_valid:
                    continue
                mels = log_mels(read_wav(raw.as_py())[1])
                on = np.zeros(len(mels) + 1, dtype=np.int64)
                for a, b in segments(mels):
                    on[a] += 1
                    on[b] -= 1
                on = np.cumsum(on)[:-1]
                values = tiles(mels)
                n = len(values)
                lengths = [min(TILE, len(mels) - TILE * i) for i in range(n)]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([key.as_py()] * n, batch.column("doc_id").type), pa.array(range(n), pa.int32()),
                        pa.array([i * TILE * step for i in range(n)], pa.float64()), pa.array([(i * TILE + k) * step for i, k in enumerate(lengths)], pa.float64()),
                        pa.array(lengths, pa.int32()), pa.array([float(on[i * TILE : (i + 1) * TILE].sum() * step) for i in range(n)], pa.float64()),
                        values.storage.cast(pa.list_(pa.float32())),
                    ],
                    ["doc_id", "tile", "start_ms", "end_ms", "n_frames", "active_ms", "values"],
                )

    kind = media.schema["doc_id"].dataType.simpleString()
    return media.select("doc_id", "media").mapInArrow(run, f"doc_id {kind}, tile int, start_ms double, end_ms double, n_frames int, active_ms double, values array<float>")


def as_tensors(values: pa.Array) -> pa.FixedShapeTensorArray:
    """The ``values`` column of a batch as Arrow tensors."""
    return pa.ExtensionArray.from_storage(TENSOR, values.cast(pa.list_(pa.float32(), TILE * BANDS)))


def store_documents(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, media): each text's payload as a stored file."""

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            raws = column_bytes(batch, "text")
            return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([len(r) for r in raws], pa.int64()), pa.array([to_wav(payload_of(r)) for r in raws], pa.binary())], ["doc_id", "n_bytes", "media"])

        return step

    kind = docs.schema["doc_id"].dataType.simpleString()
    return map_batches(docs.select("doc_id", "text"), make, f"doc_id {kind}, n_bytes bigint, media binary")


def digest(media: bytes) -> tuple[int, str, int, int, str, str]:
    """payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256 and feature of a stored file. The feature
    names frames, segments, their frames, and a hash of all tensors."""
    _, samples = read_wav(media)
    mels = log_mels(samples)
    spans = segments(mels)
    tensors = tiles(mels)
    mark = hashlib.sha256(tensors.storage.flatten().to_numpy().tobytes() + spans.tobytes()).hexdigest()[:16]
    feature = f"{len(mels)}:{len(spans)}:{int((spans[:, 1] - spans[:, 0]).sum())}:{mark}"
    return len(samples), hashlib.sha256(samples).hexdigest(), zlib.crc32(samples[-16:]), len(media), hashlib.sha256(media).hexdigest(), feature


def digest_documents(docs: DataFrame) -> DataFrame:
    """Each text stored as a file, the file read back and its features taken."""

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            rows = [digest(raw) for raw in batch.column("media").to_pylist()]
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            return pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), *(pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True))], names)

        return step

    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
    kind = docs.schema["doc_id"].dataType.simpleString()
    return map_batches(store_documents(docs), make, f"doc_id {kind}, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string", "media")
