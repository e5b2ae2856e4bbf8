"""Token counts with a whole-token shortcut.

Offline, each vocabulary string is encoded alone; those that come back as one token are *whole*, and
every task's table of pre-tokens begins with them. A pre-token that is whole counts one without any
merging. Only the rest is merged, by the library, and its counts are kept for as long as the process
lives and has room for them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .bpe import TOGETHER, encoder
from .common import as_bytes, portions, small_batches, text_or_empty


def whole_tokens(path: str) -> dict[str, int]:
    """The strings of the vocabulary that the library encodes, alone, as one token, and that. As many as the vocabulary at most."""
    library = encoder(path).library
    strings = [library.decode([i], skip_special_tokens=False) for i in range(library.get_vocab_size())]
    added = library.get_added_tokens_decoder()
    found = library.encode_batch_fast(strings, add_special_tokens=False)
    return {s: f.ids[0] for s, f in zip(strings, found) if s and len(f.ids) == 1 and f.ids[0] not in added}


def with_token_counts(docs: DataFrame, path: str, name: str, text_col: str = "text") -> DataFrame:
    """``docs`` with their token counts as a further column; one of that name is replaced."""
    docs = docs.drop(name)
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(f"`{text_col}`").alias("text"))
    return count_tokens(rows, path, "row", "text").select("id.*", F.col("n_tokens").alias(name))


def count_tokens(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, n_tokens, n_whole) of each row: UTF-8 bytes, tokens, and tokens by the shortcut. The id may be of any type.

    A null text is an empty one: no bytes, no tokens. Very long texts are counted in stretches; repeated
    rows are rows of their own, and columns beside the two that are read play no part. What is broadcast is bounded by the vocabulary.
    """
    small_batches(docs.sparkSession)
    proved = docs.sparkSession.sparkContext.broadcast(whole_tokens(path))
    rows = docs.select(docs[id_col].alias("id"), text_or_empty(text_col))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e, strings = encoder(path), [s.encode() for s in proved.value]
        ids, least = np.array(list(proved.value.values()), np.int64), 0
        for batch in batches:
            data = as_bytes(batch.column(1))
            n_tokens, n_whole = [], []
            for some in portions([x.decode("utf-8", "replace") for x in data], TOGETHER):
                n, whole = np.zeros(len(some), np.int64), np.zeros(len(some), np.int64)
                split = [i for i, t in enumerate(some) if not e.whole(t) and not any(k in t for k in e.added)]
                for i in set(range(len(some))).difference(split):
                    n[i] = len(e.encode([some[i]])[0]) // e.dtype.itemsize
                if e.table.n < least or not least:  # a new table, or one that has been aged
                    e.know(strings, ids)
                for pieces, begin, end, which in e.split([some[i] for i in split]):
                    entries = e.entries(pieces, begin, end)  # may make the table's arrays anew
                    sizes = e.table.size[entries]
                    n[split] += np.bincount(which, sizes, len(split)).astype(np.int64)
                    whole[split] += np.bincount(which, sizes == 1, len(split)).astype(np.int64)
                least = e.table.n
                e.table.age()
                n_tokens += n.tolist()
                n_whole += whole.tolist()
            counts = [pa.array(x, pa.int64()) for x in (list(map(len, data)), n_tokens, n_whole)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *counts], names=["id", "n_bytes", "n_tokens", "n_whole"])

    fields = [T.StructField(n, T.LongType()) for n in ("n_bytes", "n_tokens", "n_whole")]
    return rows.mapInArrow(count, T.StructType([T.StructField("id", rows.schema["id"].dataType), *fields]))
