"""Language identification with hyperdimensional profiles.

Every letter owns a random +-1 hypervector. A letter trigram is bound as the product of its letters'
vectors, each rotated by its place; a text is the bundle (sum) of its trigram vectors and a language
prototype the bundle of its training texts. Prediction is the prototype of largest cosine.
Non-letters fold into one blank; upper case folds into lower. Texts are taken in runs of bounded size, a long one in
pieces, so memory depends on neither the length of a text nor the number of short ones.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.shipping import arrow_map

from . import textbytes as tb

DIM = 1024
#: Texts whose bundles are held at once.
ROWS = 2048
_letters = None


def _is_letter() -> np.ndarray:
    global _letters
    if _letters is None:
        _letters = np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)
    return _letters


def letter_vectors(points: np.ndarray, dim: int = DIM) -> np.ndarray:
    """+-1 vectors of code points, drawn from a counter-based generator so that no table is kept."""
    lanes = dim // 64
    grid = points.astype(np.uint64)[:, None] * np.uint64(lanes) + np.arange(lanes, dtype=np.uint64)
    bits = np.unpackbits(tb.mix64(tb.mix64(grid + np.uint64(77)) + np.uint64(5)).view(np.uint8).reshape(len(points), -1), axis=1)
    return (bits.astype(np.int8) << 1) - 1


def trigram_vectors(codes: np.ndarray, dim: int = DIM) -> np.ndarray:
    """Bind: rotate the first letter's vector twice, the second's once, and multiply."""
    low = np.uint64((1 << 21) - 1)
    parts = [(codes >> np.uint64(42)) & low, (codes >> np.uint64(21)) & low, codes & low]
    points, back = np.unique(np.concatenate(parts), return_inverse=True)
    letters, back = letter_vectors(points, dim), back.reshape(3, -1)
    return np.roll(letters, 2, axis=1)[back[0]] * np.roll(letters, 1, axis=1)[back[1]] * letters[back[2]]


def trigrams(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(packed trigram codes, row of each). Trigrams lie in one text, with a letter in the middle."""
    low = [(t or "").lower() for t in texts]
    joined = "\n" + "\n".join(low) + "\n"
    point = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    row = np.repeat(np.arange(len(low)), [len(t) + 1 for t in low])
    row = np.concatenate([[0], row])
    code = np.where(_is_letter()[point], point, 0).astype(np.uint64)
    keep = np.ones(len(code), bool)
    keep[1:] = (code[1:] != 0) | (code[:-1] != 0)
    code, row = code[keep], row[keep]
    if len(code) < 3:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    mid = code[1:-1] != 0
    tri = (code[:-2] << np.uint64(42)) | (code[1:-1] << np.uint64(21)) | code[2:]
    return tri[mid], row[1:-1][mid]


def pieces(text: str, piece: int):
    """Packed trigram codes of one text, ``piece`` characters at a time: the same as of the whole."""
    low, carry = text.lower(), np.zeros(1, np.uint64)
    for lo in range(0, len(low) + 1, piece):
        part = low[lo : lo + piece] + ("\n" if lo + piece > len(low) else "")
        point = np.frombuffer(part.encode("utf-32-le", "surrogatepass"), np.uint32)
        code = np.concatenate([carry, np.where(_is_letter()[point], point, 0).astype(np.uint64)])
        code = code[np.concatenate([[True], (code[1:] != 0) | (code[:-1] != 0)])]
        tri = (code[:-2] << np.uint64(42)) | (code[1:-1] << np.uint64(21)) | code[2:]
        yield tri[code[1:-1] != 0]
        carry = code[-2:]


def bundles(texts: list[str], group: np.ndarray, groups: int, dim: int = DIM, piece: int = 1 << 18) -> tuple[np.ndarray, np.ndarray]:
    """(sum of trigram vectors, number of trigrams) per group of texts."""
    if len(texts) == 1 and texts[0] and len(texts[0]) > piece:
        parts = [(bundle(tri, np.zeros(len(tri), np.int64), 1, dim), len(tri)) for tri in pieces(texts[0], piece)]
        out, size = np.zeros((groups, dim)), np.zeros(groups, np.int64)
        out[group[0]], size[group[0]] = sum(p[0][0] for p in parts), sum(p[1] for p in parts)
        return out, size
    tri, row = trigrams(texts)
    return bundle(tri, group[row] if len(row) else row, groups, dim), np.bincount(group[row] if len(row) else row, minlength=groups)


def bundle(tri: np.ndarray, group: np.ndarray, groups: int, dim: int = DIM, cells: int = 1 << 22) -> np.ndarray:
    """Sum of trigram vectors per group, over slices of distinct trigrams so that a table of groups by trigrams has ``cells``."""
    out = np.zeros((groups, dim))
    if len(tri):
        step = max(64, min(8192, cells // groups))
        distinct, back = np.unique(tri, return_inverse=True)
        for lo in range(0, len(distinct), step):
            part = distinct[lo : lo + step]
            here = slice(None) if len(distinct) <= step else (back >= lo) & (back < lo + step)
            dense = np.bincount(group[here] * len(part) + (back[here] - lo), minlength=groups * len(part))
            out += dense.reshape(groups, -1).astype(np.float32) @ trigram_vectors(part, dim).astype(np.float32)
    return out


def fit(train: DataFrame, text: str = "text", lang: str = "lang", dim: int = DIM) -> tuple[list[str], np.ndarray]:
    """Prototypes from all rows of ``train`` with a language: one partial bundle per partition and
    language, added up by Spark. What reaches the driver is languages x dim numbers."""

    def partial(batches):
        total: dict[str, np.ndarray] = {}
        for b in batches:
            _, off = tb.raw(b.column(0))
            for i, j in tb.runs_of_rows(off, 1 << 20):
                langs = b.column(1).slice(i, j - i).to_pylist()
                names = sorted(set(langs))
                index = {x: k for k, x in enumerate(names)}
                sums, _ = bundles(b.column(0).slice(i, j - i).to_pylist(), np.array([index[x] for x in langs]), len(names), dim)
                for k, x in enumerate(names):
                    total[x] = total.get(x, 0) + sums[k]
        for x, v in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([x]), pa.array([v.tolist()])], names=["lang", "vec"])

    rows = train.select(F.col(text).alias("t"), F.col(lang).alias("l")).where("t is not null and l is not null")
    parts = arrow_map(rows, partial, "lang string, vec array<double>")
    sums = parts.select("lang", F.posexplode("vec").alias("at", "x")).groupBy("lang", "at").agg(F.sum("x").alias("x"))
    got = sums.groupBy("lang").agg(F.sort_array(F.collect_list(F.struct("at", "x"))).alias("v")).orderBy("lang").collect()
    return [r["lang"] for r in got], np.array([[p["x"] for p in r["v"]] for r in got]).reshape(len(got), dim)


def predict(docs: DataFrame, names: list[str], prototypes: np.ndarray, text: str = "text", keep: tuple[str, ...] = ("doc_id",), dim: int = DIM) -> DataFrame:
    """Adds lang_pred and score (cosine, cut to 0..1) to the kept columns of every row.

    Null and empty texts and texts without a letter, and every text when nothing was learnt, get ``und`` and 0.
    Ties go to the language first in order. Repeated rows are scored each on their own.
    """
    frame = docs.select(*[F.col(c).alias(f"k{i}") for i, c in enumerate(keep)], F.col(text).alias("t"))
    unit = prototypes / np.maximum(np.linalg.norm(prototypes, axis=1, keepdims=True), 1e-12) if len(names) else prototypes
    labels = np.array(names, dtype=object)
    n = len(keep)

    def score(batches):
        for b in batches:
            _, off = tb.raw(b.column(n))
            pred, best = [], []
            for i, j in tb.runs_of_rows(off, 1 << 18, ROWS):
                v, found = bundles(b.column(n).slice(i, j - i).to_pylist(), np.arange(j - i), j - i, dim)
                size = np.linalg.norm(v, axis=1)
                if not len(names):
                    pred += ["und"] * (j - i)
                    best += [0.0] * (j - i)
                    continue
                cos = (v @ unit.T) / np.maximum(size, 1e-12)[:, None]
                top = cos.argmax(axis=1)
                has = found > 0
                pred += np.where(has, labels[top], "und").tolist()
                best += np.where(has, np.clip(cos[np.arange(j - i), top], 0, 1), 0.0).tolist()
            yield pa.RecordBatch.from_arrays([*b.columns[:n], pa.array(pred, pa.string()), pa.array(best, pa.float64())], schema=None, names=[*[f"k{i}" for i in range(n)], "lang_pred", "score"])

    kinds = dict(frame.dtypes)
    out = arrow_map(frame, score, ", ".join([*[f"k{i} {kinds[f'k{i}']}" for i in range(n)], "lang_pred string", "score double"]))
    return out.select(*[F.col(f"k{i}").alias(c) for i, c in enumerate(keep)], "lang_pred", "score")


def language_id(docs: DataFrame) -> DataFrame:
    """The contract's query: learn from rows whose id hash modulo 4 is not 2, predict all rows.
    A null id hashes to null and counts as not held out. Empty tables give empty results; nulls and repeats as in ``predict``."""
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))
    names, prototypes = fit(docs.where(~held))
    out = predict(docs.withColumn("held_out", held), names, prototypes, keep=("doc_id", "held_out"))
    return out
