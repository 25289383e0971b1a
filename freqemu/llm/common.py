"""What the operators share: text as bytes, vectorised words, Arrow passes over rows."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, functions as F, types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: Bytes that part words under the two word definitions of the contracts.
SPACES = bytes([*range(9, 14), 32])
LETTERS_AND_DIGITS = b"0123456789abcdefghijklmnopqrstuvwxyz"


def _table(is_word: Callable[[int], bool]) -> bytes:
    """A translation table: A-Z to lower case, bytes outside words to a blank."""
    lower = bytes(range(256)).lower()
    return bytes(c if is_word(c) else 32 for c in lower)


#: Runs of anything but white space, and runs of digits, letters and non-ASCII characters.
SPACED = _table(lambda c: c not in SPACES)
ALNUM = _table(lambda c: c >= 128 or c in LETTERS_AND_DIGITS)
SPACED_SET = r"[^\x20\x09-\x0D]+"
ALNUM_SET = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

#: Rows and bytes of text handled at once inside an Arrow batch, to bound memory; one longer text is handled by itself.
SLICE, SLICE_BYTES = 512, 2 << 20
#: Bytes that WordHasher turns into numbers at once.
PIECE = 1 << 20


def words(text: bytes | None, table: bytes) -> list[bytes]:
    return text.translate(table).split() if text else []


def held_out(doc_id: Column, parts: int, part: int) -> Column:
    """True for documents that no model may learn from; a null id is never held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % parts == part, F.lit(False))


def learnable(doc_id: Column, parts: int, part: int) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % parts != part, F.lit(False))


def slices(sizes: np.ndarray, rows: int = SLICE, most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges [a, b) of up to ``rows`` places whose sizes sum to ``most`` or less, or of one place."""
    ends, a = np.cumsum(sizes), 0
    while a < len(sizes):
        before = ends[a - 1] if a else 0
        b = max(a + 1, min(a + rows, int(np.searchsorted(ends, before + most, side="right"))))
        yield a, b
        a = b


def lengths(column: pa.Array) -> np.ndarray:
    """Bytes of each value of a string or binary column (null: 0); 1 for values of other types."""
    if not (pa.types.is_string(column.type) or pa.types.is_large_string(column.type) or pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type)):
        return np.ones(len(column), np.int64)
    return pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)


def free_names(fields: Sequence[str], taken: Sequence[str]) -> list[str]:
    """``fields``, each with as many underscores behind it as make it differ from ``taken``."""
    used = {t.lower() for t in taken}
    out = []
    for f in fields:
        while f.lower() in used:
            f += "_"
        used.add(f.lower())
        out.append(f)
    return out


def annotate(
    df: DataFrame,
    inputs: Sequence[str],
    fields: Sequence[tuple[str, T.DataType]],
    start: Callable[[], Callable[..., Sequence]],
    keep: Sequence[str] | None = None,
) -> DataFrame:
    """Rows of ``df`` with computed columns behind the kept ones, in one pass without shuffle.

    ``start`` runs once in each task and gives a function; that function gets the
    ``inputs`` of up to SLICE rows and SLICE_BYTES as lists (strings as UTF-8 bytes, null as None) and
    returns one sequence or Arrow array for each field. Computed columns whose names a kept column has
    get underscores behind them. ``keep`` defaults to every column.
    """
    kept = list(df.columns) if keep is None else list(keep)
    names = free_names([n for n, _ in fields], kept)
    source = df.select(*[F.col(f"`{c}`") for c in dict.fromkeys([*kept, *inputs])])
    at = {c: i for i, c in enumerate(source.columns)}
    kept_at, input_at = [at[c] for c in kept], [at[c] for c in inputs]
    schema = T.StructType([source.schema[i] for i in kept_at] + [T.StructField(n, t) for n, (_, t) in zip(names, fields)])
    arrow = to_arrow_schema(schema)
    n_kept = len(kept_at)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = start()
        for batch in batches:
            for a, b in slices(sum((lengths(batch.column(i)) for i in input_at), np.zeros(batch.num_rows, np.int64))):
                part = batch.slice(a, b - a)
                cols = []
                for i in input_at:
                    c = part.column(i)
                    if pa.types.is_string(c.type) or pa.types.is_large_string(c.type):
                        c = c.cast(pa.binary() if pa.types.is_string(c.type) else pa.large_binary())
                    cols.append(c.to_pylist())
                made = work(*cols)
                arrays = [part.column(i) for i in kept_at]
                arrays += [v if isinstance(v, pa.Array) else pa.array(v, type=arrow.field(n_kept + k).type) for k, v in enumerate(made)]
                yield pa.RecordBatch.from_arrays(arrays, names=arrow.names)

    return source.mapInArrow(run, schema)


# -- vectorised words -------------------------------------------------------------------

_MIX_1, _MIX_2 = 0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53
_RADIX = 0x9E3779B97F4A7C15 | 1


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(_MIX_1)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(_MIX_2)
    return x ^ (x >> np.uint64(33))


class WordHasher:
    """64-bit hashes of all words of many texts, nearly all without a Python object for each word.

    Words of up to seven bytes are told apart exactly: their bytes and their length fill one
    number, which a bijection spreads. Longer words have xxh3 hashes of their bytes. Pieces
    of the buffer that are worked on at once end between words.
    """

    def __init__(self, table: bytes):
        self.table = table

    def _piece(self, buffer: bytes, a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        text = np.frombuffer(buffer, np.uint8, b - a, a)
        edge = np.flatnonzero(np.diff(text != 32, prepend=False, append=False))
        first, size = edge[::2], edge[1::2] - edge[::2]
        value = np.ndarray(b - a, "<u8", buffer, a, (1,))[first].astype(np.uint64)
        bits = np.minimum(size, 7).astype(np.uint64) << np.uint64(3)
        value &= (np.uint64(1) << bits) - np.uint64(1)
        hashes = mix(value | (bits << np.uint64(53)))
        long = np.flatnonzero(size > 7)
        ends = zip((first[long] + a).tolist(), (first[long] + size[long] + a).tolist())
        hashes[long] = np.fromiter((xxhash.xxh3_64_intdigest(buffer[x:y]) for x, y in ends), np.uint64, len(long))
        return hashes, first + a

    def __call__(self, texts: Sequence[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all words in order, and for each text the number of words before it (and all at the end)."""
        sizes = np.fromiter((len(t) + 1 if t else 1 for t in texts), np.int64, len(texts))
        buffer = (b" ".join([t or b"" for t in texts]) + b" " * 8).translate(self.table)
        hashes, firsts, a = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], 0
        size = len(buffer) - 7
        while a < size:
            b = min(buffer.find(b" ", min(a + PIECE, size) - 1) + 1, size)
            h, first = self._piece(buffer, a, b)
            hashes.append(h)
            firsts.append(first)
            a = b
        return np.concatenate(hashes), np.searchsorted(np.concatenate(firsts), np.concatenate([[0], np.cumsum(sizes)]))


def shingles(hashes: np.ndarray, width: int) -> np.ndarray:
    """The sorted distinct hashes of ``width`` consecutive words; of the whole sequence if it is shorter."""
    n = len(hashes)
    if n == 0:
        return hashes
    take = min(width, n)
    out = np.full(n - take + 1, take, np.uint64)
    for k in range(take):
        out = mix(out * np.uint64(_RADIX) + hashes[k : n - take + 1 + k])
    return np.unique(out)
