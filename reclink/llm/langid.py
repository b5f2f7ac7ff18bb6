"""Language identification by a byte convolutional network.

Training: windows of 128 bytes from whole texts with a known language (a bounded sample:
about `docs_per_language` texts of each language, `windows_per_doc` windows of each).
Bytes (A-Z lowered, NUL as padding) are embedded; filters of widths two, three and four
run over the window, their responses go through a rectifier and a maximum over the
window, and a softmax layer follows.  numpy computes the gradients; Adam takes the steps.

Prediction: every byte of every text.  A text is padded to whole windows; a filter's
response is a sum of terms that depend on two bytes or one, so the trained network is
turned into lookup tables by byte pairs (fixed point), and the windows of a batch go
through gathers, maxima and one matrix product.  A text's probabilities are the means of
its windows', weighted by their bytes.

Null texts and texts without a letter get `und` and score 0; so do all if no labelled
text is there to learn from.  Of languages with equal probabilities the first by name wins.
Repeated rows are judged row by row.  Empty tables give no rows.  Further columns, whatever
their names, are kept by `keep_known` and ignored by `predict`.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reclink.llm._common import bounded, materialise, text_steps, tidy

WINDOW = 128
WIDTHS = (2, 3, 4)
FILTERS, EMBED = 12, 12
DOCS_PER_LANGUAGE, WINDOWS_PER_DOC = 500, 6
UNKNOWN = "und"
#: Keys of 16 bytes each, so at most 8 MB are broadcast.
BROADCAST_ROWS = 500_000

_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] = _FOLD[97:123]


# ---------------------------------------------------------------- training
def _start(classes: int, rng: np.random.Generator) -> dict[str, np.ndarray]:
    p = {"embed": rng.normal(0, 0.5, (256, EMBED))}
    for w in WIDTHS:
        p[f"filter{w}"] = rng.normal(0, (w * EMBED) ** -0.5, (w, EMBED, FILTERS))
        p[f"bias{w}"] = np.zeros(FILTERS)
    p["out"] = rng.normal(0, 0.2, (len(WIDTHS) * FILTERS, classes))
    p["out_bias"] = np.zeros(classes)
    return {k: v.astype(np.float32) for k, v in p.items()}


def _gradients(p: dict, x: np.ndarray, y: np.ndarray) -> tuple[float, dict]:
    n, length = x.shape
    e = p["embed"][x]
    pooled, places = [], []
    for w in WIDTHS:
        steps = length - w + 1
        r = sum((e[:, t : t + steps].reshape(-1, EMBED) @ p[f"filter{w}"][t]).reshape(n, steps, FILTERS) for t in range(w))
        at = r.argmax(axis=1)
        places.append(at)
        pooled.append(np.take_along_axis(r, at[:, None], 1)[:, 0] + p[f"bias{w}"])
    z = np.concatenate(pooled, axis=1)
    h = np.maximum(z, 0)
    s = h @ p["out"] + p["out_bias"]
    s = np.exp(s - s.max(axis=1, keepdims=True))
    s /= s.sum(axis=1, keepdims=True)
    loss = float(-np.log(s[np.arange(n), y] + 1e-9).mean())
    s[np.arange(n), y] -= 1
    s /= n
    g = {"out": h.T @ s, "out_bias": s.sum(axis=0), "embed": np.zeros_like(p["embed"])}
    back = (s @ p["out"].T) * (z > 0)
    for k, w in enumerate(WIDTHS):
        b = back[:, k * FILTERS : (k + 1) * FILTERS]
        g[f"bias{w}"] = b.sum(axis=0)
        grad = np.zeros_like(p[f"filter{w}"])
        for t in range(w):
            spot = places[k] + t
            seen = np.take_along_axis(x, spot, 1)
            grad[t] = np.einsum("nfe,nf->ef", p["embed"][seen], b)
            np.add.at(g["embed"], seen, b[:, :, None] * p[f"filter{w}"][t].T[None])
        g[f"filter{w}"] = grad
    return loss, g


def fit(windows: np.ndarray, labels: np.ndarray, classes: int, rounds: int = 900, batch: int = 64, rate: float = 0.01, seed: int = 3) -> dict[str, np.ndarray]:
    """Train on windows (n x WINDOW bytes, folded) and labels 0..classes-1."""
    rng = np.random.default_rng(seed)
    p = _start(classes, rng)
    m = {k: np.zeros_like(v) for k, v in p.items()}
    v = {k: np.zeros_like(x) for k, x in p.items()}
    by_class = [np.flatnonzero(labels == c) for c in range(classes)]
    for step in range(1, rounds + 1):
        take = np.concatenate([rng.choice(rows, max(1, batch // classes)) for rows in by_class])
        _, g = _gradients(p, windows[take], labels[take])
        speed = rate * min(1.0, 3 * (1 - step / (rounds + 1))) * np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
        for k in p:
            m[k] = 0.9 * m[k] + 0.1 * g[k]
            v[k] = 0.999 * v[k] + 0.001 * g[k] ** 2
            p[k] -= speed * m[k] / (np.sqrt(v[k]) + 1e-8)
    return p


# ---------------------------------------------------------------- prediction
class Tables:
    """The trained filters as fixed-point responses of byte pairs and single bytes."""

    def __init__(self, p: dict[str, np.ndarray]):
        e = p["embed"][_FOLD].astype(np.float64)
        parts = {w: [e @ p[f"filter{w}"][t] for t in range(w)] for w in WIDTHS}
        pair = lambda a, b: (a[:, None] + b[None]).reshape(65536, FILTERS)
        raw = {"two": pair(*parts[2]), "three": pair(*parts[3][:2]), "third": parts[3][2], "four": pair(*parts[4][:2]), "rest": pair(*parts[4][2:])}
        self.unit = 16000 / max(np.abs(x).max() for x in raw.values())
        for name, x in raw.items():
            setattr(self, name, np.ascontiguousarray(np.round(x * self.unit).astype(np.int16)))
        self.bias = np.concatenate([p[f"bias{w}"] for w in WIDTHS])
        self.out, self.out_bias = p["out"], p["out_bias"]

    @staticmethod
    def _most(r: np.ndarray) -> np.ndarray:
        while r.shape[1] > 1:
            half = (r.shape[1] + 1) // 2
            r = np.maximum(r[:, :half], r[:, r.shape[1] - half :])
        return r[:, 0]

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        """Softmax outputs of windows (n x WINDOW bytes)."""
        two = (x[:, :-1].astype(np.int32) << 8) | x[:, 1:]
        best = [
            self._most(self.two[two]),
            self._most(self.three[two[:, :-1]] + self.third[x[:, 2:]]),
            self._most(self.four[two[:, :-2]] + self.rest[two[:, 2:]]),
        ]
        h = np.maximum(np.concatenate(best, axis=1) / self.unit + self.bias, 0)
        s = h @ self.out + self.out_bias
        s = np.exp(s - s.max(axis=1, keepdims=True))
        return s / s.sum(axis=1, keepdims=True)


def _windows(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Texts padded to whole windows: (windows, windows of each text, bytes of each window)."""
    sizes = np.diff(offsets)
    count = -(-sizes // WINDOW)
    out = np.zeros(int(count.sum()) * WINDOW, np.uint8)
    at = 0
    for a, n, k in zip(offsets[:-1].tolist(), sizes.tolist(), count.tolist()):
        out[at : at + n] = data[a : a + n]
        at += k * WINDOW
    last = np.cumsum(count)
    weight = np.full(int(count.sum()), WINDOW)
    full = count > 0
    weight[last[full] - 1] = sizes[full] - (count[full] - 1) * WINDOW
    return out.reshape(-1, WINDOW), count, weight


_ASCII_LETTER = np.zeros(256, bool)
_ASCII_LETTER[[*range(65, 91), *range(97, 123)]] = True


def _lettered(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    seen = np.concatenate([[0], np.cumsum(_ASCII_LETTER[data])])
    out = seen[offsets[1:]] > seen[offsets[:-1]]
    for k in np.flatnonzero(~out):
        out[k] = any(c.isalpha() for c in data[offsets[k] : offsets[k + 1]].tobytes().decode("utf-8", "replace"))
    return out


def sample(docs: DataFrame, docs_per_language: int = DOCS_PER_LANGUAGE, windows_per_doc: int = WINDOWS_PER_DOC) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(languages, windows, labels) of a bounded sample of docs (doc_id, text, lang).

    Each language gives its texts by the hash of their doc_id, about docs_per_language of
    them; every language that labels a text is learned.
    """
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    counts = known.groupBy("lang").count().collect()
    if not counts:
        return [], np.zeros((0, WINDOW), np.uint8), np.zeros(0, np.int64)
    languages = sorted(r["lang"] for r in counts)
    share = F.create_map(*[F.lit(x) for r in counts for x in (r["lang"], min(1.0, docs_per_language / r["count"]))])
    drawn = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < share[F.col("lang")] * float(1 << 30)).select("lang", "text")

    def cut(batches):
        for batch in batches:
            for at, to, data, offsets in text_steps(batch.column(1)):
                found, names = [], []
                for lang, a, b in zip(batch.column(0).slice(at, to - at).to_pylist(), offsets[:-1].tolist(), offsets[1:].tolist()):
                    spots = np.unique(np.linspace(a, max(a, b - WINDOW), windows_per_doc).astype(int))
                    for s in spots.tolist() if b > a else []:
                        found.append(data[s : min(b, s + WINDOW)].tobytes().ljust(WINDOW, b"\0"))
                        names.append(lang)
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(found, pa.binary())], names=["lang", "window"])

    table = drawn.mapInArrow(tidy(cut), "lang string, window binary").toArrow()
    order = np.lexsort([table["window"].to_numpy(zero_copy_only=False), table["lang"].to_numpy(zero_copy_only=False)]) if table.num_rows else []
    x = np.frombuffer(b"".join(table["window"].to_pylist()), np.uint8).reshape(-1, WINDOW)
    y = np.array([languages.index(v) for v in table["lang"].to_pylist()], np.int64)
    return languages, _FOLD[x[order]] if len(x) else x, y[order] if len(y) else y


def train(docs: DataFrame, **bounds) -> tuple[list[str], dict[str, np.ndarray] | None]:
    languages, x, y = sample(docs, **bounds)
    present = sorted(set(y.tolist()))
    if not present:
        return [], None
    languages = [languages[c] for c in present]
    return languages, fit(x, np.searchsorted(present, y), len(languages))


def _judge(column, tables: Tables | None, languages: int, block: int):
    """Per step of texts: (first row, end, index of the language or `languages`, score, whether
    there is a letter)."""
    for at, to, data, offsets in text_steps(column, 1 << 20):
        known = _lettered(data, offsets)
        best, score = np.full(to - at, languages), np.zeros(to - at)
        if tables and known.any():
            x, count, weight = _windows(data, offsets)
            per = max(1, block // WINDOW)
            p = np.concatenate([tables.probabilities(x[i : i + per]) for i in range(0, len(x), per)]) * weight[:, None]
            sums = np.vstack([np.zeros(p.shape[1]), np.cumsum(p, axis=0)])
            stop = np.cumsum(count)
            mean = (sums[stop] - sums[stop - count]) / np.maximum(np.diff(offsets), 1)[:, None]
            best = np.where(known, mean.argmax(axis=1), best)
            score = np.where(known, np.clip(mean.max(axis=1), 0, 1), 0)
        yield at, to, best, np.round(score, 9), known


def predict(docs: DataFrame, model: tuple[list[str], dict[str, np.ndarray] | None], block: int = 256 << 10) -> DataFrame:
    """Per row of docs (doc_id, text): doc_id, lang_pred and score."""
    languages, parameters = model

    def apply(batches):
        tables = Tables(parameters) if parameters else None
        names = np.array([*languages, UNKNOWN], object)
        for batch in batches:
            for at, to, best, score, _ in _judge(batch.column(1), tables, len(languages), block):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, to - at), pa.array(names[best], pa.string()), pa.array(score)], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(tidy(apply), "doc_id long, lang_pred string, score double")


def keep_known(docs: DataFrame, model, least: float = 0.3, block: int = 256 << 10) -> DataFrame:
    """The rows of docs, with all their columns, whose text has a language: not `und`, and
    no score under `least`; without a model (no labelled text), all that have a letter.  Only
    keys of the others come out of the network; they are broadcast if they are few."""
    languages, parameters = model

    def judge(batches):
        tables = Tables(parameters) if parameters else None
        for batch in batches:
            for at, to, best, score, known in _judge(batch.column(1), tables, len(languages), block):
                gone = pa.array((best == len(languages)) | (score < least) if tables else ~known)
                yield pa.RecordBatch.from_arrays([batch.column(k).slice(at, to - at).filter(gone) for k in (0, 2)], names=["_gone", "_k"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("k"))
    gone = bounded(materialise(rows.mapInArrow(tidy(judge), "_gone long, _k long").distinct(), "no-language"), BROADCAST_ROWS)
    same = docs["doc_id"].eqNullSafe(gone["_gone"]) & (F.xxhash64(docs["text"]) == gone["_k"])
    return docs.join(gone, same, "left_anti")
