"""Language identification by hyperdimensional profiles.

Every letter has a random bipolar vector; a trigram is the product of its letters'
vectors, each rotated by its place; a text is the sum of its trigrams.  The sum over a
language's training texts is its prototype, and a text has the language whose
prototype has the highest cosine with it.

``accepted`` keeps what some prototype knows: a text of ``ENOUGH`` letters or more goes if its best
cosine is below ``REJECT``, which in 512 dimensions is what random letters reach with some language
(0.04 is one standard deviation); shorter texts say too little and stay if they have a letter.

Defined cases: null text or a text without a letter is ``und`` with score 0, as is any
text if nothing was learnt (``accepted`` then keeps all that has a letter); ties go to the
alphabetically first language; rows that repeat an id, and rows with a null id, are judged each on their
own; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .words import slices

DIMENSIONS = 512
SYMBOLS = 64  # 0: not a letter; 1-26: a-z; the others share what is left
UNKNOWN = "und"
ENOUGH, REJECT = 100, 0.13  # letters, cosine
SEED = 20240501


@lru_cache(1)
def _symbols() -> np.ndarray:
    """Symbol of each code point."""
    out = np.zeros(0x110000, np.uint8)
    for c in range(0x110000):
        if (x := chr(c)).isalpha():
            low = ord(x.lower()[0])
            out[c] = low - 96 if 97 <= low <= 122 else 27 + low * 2654435761 % 4294967296 % (SYMBOLS - 27)
    return out


@lru_cache(1)
def _letters() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Vectors of the symbols at each of the three places."""
    v = np.random.default_rng(SEED).integers(0, 2, (SYMBOLS, DIMENSIONS)).astype(np.float32) * 2 - 1
    return np.roll(v, 2, axis=1), np.roll(v, 1, axis=1), v


def trigram_vectors(codes: np.ndarray) -> np.ndarray:
    a, b, c = _letters()
    return a[codes >> 12] * b[codes >> 6 & 63] * c[codes & 63]


def trigrams(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Codes of all trigrams, the text of each, and the number of letters of every text."""
    size = np.fromiter(map(len, texts), np.int64, len(texts))
    cps = np.frombuffer("".join([f"\n{t}\n" for t in texts]).encode("utf-32-le", "surrogatepass"), np.uint32)
    doc = np.repeat(np.arange(len(texts)), size + 2)
    x = _symbols()[cps]
    keep = x != 0
    letters = np.bincount(doc[keep], minlength=len(texts))
    keep[1:] |= (x[:-1] != 0) | (doc[1:] != doc[:-1])
    keep[:1] = True
    x, doc = x[keep].astype(np.int64), doc[keep]
    inside = doc[2:] == doc[:-2]
    return ((x[:-2] << 12) + (x[1:-1] << 6) + x[2:])[inside], doc[2:][inside], letters


def bundles(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """The vector of each text and its number of letters."""
    codes, doc, letters = trigrams(texts)
    used = np.flatnonzero(np.bincount(codes, minlength=SYMBOLS**3))
    row = np.zeros(SYMBOLS**3, np.int64)
    row[used] = np.arange(len(used))
    counts = np.bincount(doc * max(1, len(used)) + row[codes], minlength=len(texts) * len(used)).reshape(len(texts), len(used)).astype(np.float32)
    return counts @ trigram_vectors(used), letters


def _learn(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sums: dict[str, np.ndarray] = {}
    for batch in batches:
        for rows, col in slices(batch, limit=1 << 20):
            langs = np.array(rows.column(0).to_pylist(), object)
            codes, doc, _ = trigrams(col.to_pylist())
            for lang in sorted(set(langs)):
                mine = np.bincount(codes[(langs == lang)[doc]], minlength=SYMBOLS**3)
                sums[lang] = sums[lang] + mine if lang in sums else mine
    for lang, counts in sums.items():
        used = np.flatnonzero(counts)
        total = np.zeros(DIMENSIONS)
        for lo in range(0, len(used), 4096):
            part = used[lo : lo + 4096]
            total += counts[part].astype(np.float64) @ trigram_vectors(part)
        yield pa.RecordBatch.from_arrays([pa.array([lang]), pa.array([total.round().astype(np.int64).tolist()], pa.list_(pa.int64()))], ["lang", "v"])


def learn(train: DataFrame, text_col: str = "text", lang_col: str = "lang") -> dict[str, np.ndarray]:
    """Prototypes from all rows with a language; each task sends one vector per language."""
    rows = train.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).alias("text"))
    parts = rows.mapInArrow(_learn, "lang string, v array<bigint>").select("lang", F.posexplode("v").alias("d", "x"))
    out: dict[str, np.ndarray] = {}
    for r in parts.groupBy("lang", "d").agg(F.sum("x").alias("x")).collect():
        out.setdefault(r["lang"], np.zeros(DIMENSIONS))[r["d"]] = r["x"]
    return dict(sorted(out.items()))


def _judged(texts: list[str], unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Number of letters, best prototype and its cosine (0 without letters or prototypes)."""
    v, letters = bundles(texts)
    if not len(unit):
        return letters, np.zeros(len(texts), np.int64), np.zeros(len(texts))
    v = v.astype(np.float64)
    norm = np.sqrt((v * v).sum(1))
    cos = (v @ unit.T) / np.where(norm > 0, norm, 1)[:, None]
    best = cos.argmax(1)
    return letters, best, np.where(letters > 0, np.clip(cos[np.arange(len(best)), best], 0, 1), 0.0)


def _predict(names: list[str], unit: np.ndarray):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labels = np.array([*names, UNKNOWN], object)
        for batch in batches:
            for rows, col in slices(batch, limit=1 << 20):
                letters, best, score = _judged(col.to_pylist(), unit)
                pred = labels[np.where((letters > 0) & bool(names), best, len(names))]
                keep = [rows.column(i) for i in range(rows.num_columns) if rows.schema.names[i] != "text"]
                cols = [x for x in rows.schema.names if x != "text"]
                yield pa.RecordBatch.from_arrays([*keep, pa.array(pred, pa.string()), pa.array(score)], [*cols, "lang_pred", "score"])

    return run


def _units(prototypes: dict[str, np.ndarray]) -> np.ndarray:
    return np.array([v / max(1e-300, np.linalg.norm(v)) for v in prototypes.values()]).reshape(len(prototypes), DIMENSIONS)


def accepted(docs: DataFrame, prototypes: dict[str, np.ndarray], text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, whose text is in one of the learnt languages; see above for short ones."""
    unit = _units(prototypes)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, col in slices(batch, text_col, 1 << 20):
                letters, _, score = _judged(col.to_pylist(), unit)
                yield rows.filter(pa.array((letters > 0) & ((letters < ENOUGH) | (score >= REJECT) | (not len(unit)))))

    return docs.mapInArrow(run, docs.schema)


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, lang_pred, score for every row; the text is the only input."""
    names, unit = list(prototypes), _units(prototypes)
    rows = docs.select(F.col(id_col), F.col(text_col).alias("text"))
    kind = rows.schema[0].dataType.simpleString()
    return rows.mapInArrow(_predict(names, unit), f"`{id_col}` {kind}, lang_pred string, score double")


def held_out(id_column: Column, modulus: int = 4, remainder: int = 2) -> Column:
    return F.coalesce(F.crc32(id_column.cast("string")) % modulus == remainder, F.lit(False))
