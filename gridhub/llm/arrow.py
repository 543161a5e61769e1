"""Arrow helpers shared by the Python-side text operators."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Fixed value: white space outside ASCII's six, as a pattern.
BLANKS = r"[\x{1c}-\x{1f}\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]"
#: Bytes of text handled at a time in one Python worker.
SLICE_BYTES = 4 << 20


def text_slices(batches: Iterator[pa.RecordBatch], text: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that each slice holds about ``limit`` bytes of text.

    A single longer text stays whole in a slice of its own.  Empty batches vanish.
    """
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(text))), 0)
        block = np.cumsum(sizes.to_numpy(zero_copy_only=False).astype(np.int64)) // limit
        starts = np.flatnonzero(np.r_[True, block[1:] != block[:-1]])
        for a, b in zip(starts, np.r_[starts[1:], batch.num_rows]):
            yield batch.slice(int(a), int(b - a))


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def filled(batch: pa.RecordBatch, name: str = "text") -> pa.Array:
    """The text column with null read as the empty string."""
    return pc.fill_null(column(batch, name), "")


def word_lists(texts: pa.Array, unicode: bool = False) -> tuple[np.ndarray, pa.Array]:
    """Split on ASCII (or all) white space: list offsets and the flat array of non-empty words.

    The library's own split on Unicode white space now and then misses a blank at the very
    end of its buffer, so other blanks become ASCII ones first.
    """
    lists = pc.ascii_split_whitespace(pc.replace_substring_regex(texts, BLANKS, " ") if unicode else texts)
    flat = lists.flatten()
    counts = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
    full = pc.binary_length(flat).to_numpy(zero_copy_only=False) > 0
    if not full.all():
        kept = np.r_[0, np.cumsum(full)]
        ends = np.cumsum(counts)
        counts = kept[ends] - kept[ends - counts]
        flat = flat.filter(pa.array(full))
    return np.r_[0, np.cumsum(counts)], flat
