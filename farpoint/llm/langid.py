"""Language identification with a convolutional network over bytes, trained here in numpy.

Texts are cut into windows of fixed length. Filters of several widths run over the byte
embeddings of a window, each keeps its maximum, and a softmax layer turns the maxima into language
probabilities; a text's are the mean of its windows', weighted by their bytes. As a filter over
embedded bytes is a sum of table rows, prediction adds rows of byte-pair tables.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LENGTH = 256
WIDTHS = (2, 3, 4)
EMBED = 8
FILTERS = 16
#: Bounds of the training sample: labelled rows over all languages, and windows of each.
SAMPLE_ROWS = 2400
SAMPLE_WINDOWS = 4
EPOCHS = 6
BATCH = 64
#: Windows predicted at once.
CHUNK = 128
UNKNOWN = "und"


class ByteNet:
    def __init__(self, classes: list[str], seed: int = 0):
        rng = np.random.default_rng(seed)
        self.classes = classes
        self.p = {"embed": rng.normal(0, 0.5, (256, EMBED)), "out": rng.normal(0, 0.1, (len(WIDTHS) * FILTERS, len(classes))), "bias": np.zeros(len(classes))}
        for w in WIDTHS:
            self.p[f"conv{w}"] = rng.normal(0, 1 / np.sqrt(w * EMBED), (w, EMBED, FILTERS))
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}

    def _tables(self) -> dict[int, np.ndarray]:
        """For each width (w, 256, FILTERS): what a byte at each place of a filter adds."""
        return {w: self.p["embed"] @ self.p[f"conv{w}"] for w in WIDTHS}

    def step(self, x: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        tables, pooled, places = self._tables(), [], []
        for w in WIDTHS:
            z = sum(tables[w][j][x[:, j : LENGTH - w + 1 + j]] for j in range(w))
            places.append(z.argmax(1))
            pooled.append(np.take_along_axis(z, places[-1][:, None], 1)[:, 0])
        h = np.maximum(np.concatenate(pooled, 1), 0)
        prob = softmax(h @ self.p["out"] + self.p["bias"])
        loss = -float(np.log(prob[np.arange(len(y)), y] + 1e-9).mean())
        d = prob.copy()
        d[np.arange(len(y)), y] -= 1
        d /= len(y)
        grad = {"out": h.T @ d, "bias": d.sum(0), "embed": np.zeros_like(self.p["embed"])}
        dh = (d @ self.p["out"].T) * (h > 0)
        for i, w in enumerate(WIDTHS):
            g, at = dh[:, i * FILTERS : (i + 1) * FILTERS], places[i]
            grad[f"conv{w}"] = np.zeros_like(self.p[f"conv{w}"])
            for j in range(w):
                dt = np.zeros((256, FILTERS), np.float32)
                np.add.at(dt, (np.take_along_axis(x, at + j, 1), np.arange(FILTERS)[None, :]), g)
                grad[f"conv{w}"][j] = self.p["embed"].T @ dt
                grad["embed"] += dt @ self.p[f"conv{w}"][j].T
        return loss, grad

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = EPOCHS, rate: float = 0.01, seed: int = 0) -> None:
        rng = np.random.default_rng(seed)
        first, second, t = {k: np.zeros_like(v) for k, v in self.p.items()}, {k: np.zeros_like(v) for k, v in self.p.items()}, 0
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for lo in range(0, len(x), BATCH):
                pick = order[lo : lo + BATCH]
                _, grad = self.step(x[pick], y[pick])
                t += 1
                for k, g in grad.items():
                    first[k] = 0.9 * first[k] + 0.1 * g
                    second[k] = 0.999 * second[k] + 0.001 * g * g
                    self.p[k] -= (rate * (first[k] / (1 - 0.9**t)) / (np.sqrt(second[k] / (1 - 0.999**t)) + 1e-8)).astype(np.float32)

    def predictor(self):
        """windows (n, LENGTH) uint8 -> probabilities (n, classes)."""
        t = self._tables()
        pair = lambda a, b: np.ascontiguousarray((a[:, None, :] + b[None, :, :]).reshape(65536, FILTERS))
        two, three, four, rest = pair(t[2][0], t[2][1]), pair(t[3][0], t[3][1]), pair(t[4][0], t[4][1]), pair(t[4][2], t[4][3])
        one, out, bias = np.ascontiguousarray(t[3][2]), self.p["out"], self.p["bias"]

        def run(x: np.ndarray) -> np.ndarray:
            pairs = x[:, :-1].astype(np.int32) * 256 + x[:, 1:]
            rows = lambda table, at: np.take(table, at, axis=0, mode="clip")
            h2 = rows(two, pairs).max(1)
            z = rows(three, pairs[:, :-1])
            z += rows(one, x[:, 2:].astype(np.int32))
            h3 = z.max(1)
            z = rows(four, pairs[:, :-2])
            z += rows(rest, pairs[:, 2:])
            return softmax(np.maximum(np.concatenate([h2, h3, z.max(1)], 1), 0) @ out + bias)

        return run


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def windows_of(text: bytes) -> np.ndarray:
    n = max(1, -(-len(text) // LENGTH))
    return np.frombuffer(text.ljust(n * LENGTH), np.uint8).reshape(n, LENGTH)


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 4 == 2


def train(docs: DataFrame, sample_rows: int = SAMPLE_ROWS, seed: int = 0) -> ByteNet | None:
    """Fits on a bounded sample, spread evenly over the languages; rows are picked by a hash of the id."""
    known = docs.where(~held_out(F.col("doc_id")) & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "lang", "text")
    sizes = {r.lang: r.n for r in known.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not sizes:
        return None
    classes, steps = sorted(sizes), 1 << 30
    quota = max(1, sample_rows // len(classes))
    share = F.create_map(*[F.lit(v) for c in classes for v in (c, min(steps, 2 * quota * steps // sizes[c] + 1))])
    draw = F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.lit(steps))
    spaced = F.expr(f"transform(sequence(0, {SAMPLE_WINDOWS - 1}), i -> substring(text, cast(1 + i * greatest(length(text) - {LENGTH}, 0) / {max(SAMPLE_WINDOWS - 1, 1)} as int), {LENGTH}))")
    rows = known.where(draw < share[F.col("lang")]).select("lang", draw.alias("draw"), spaced.alias("pieces")).orderBy("draw").limit(2 * sample_rows).collect()
    left, x, y = dict.fromkeys(classes, quota), [], []
    for r in rows:
        if left[r.lang]:
            left[r.lang] -= 1
            for piece in dict.fromkeys(r.pieces):
                x.append(windows_of(piece.encode("utf-8", "surrogatepass")[:LENGTH])[0])
                y.append(classes.index(r.lang))
    net = ByteNet(classes, seed)
    net.fit(np.array(x).astype(np.int64), np.array(y), seed=seed)
    return net


class Predictor:
    """Languages and scores of a batch of texts."""

    def __init__(self, net: ByteNet | None):
        self.net, self.run = net, net.predictor() if net else None

    def __call__(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        net, n_texts = self.net, len(texts)
        total = np.zeros((n_texts, len(net.classes) if net else 1))
        size, letters = np.zeros(n_texts), np.zeros(n_texts, bool)
        held, owner, weight, n = [], [], [], 0

        def flush():
            x, who, w = np.concatenate(held), np.concatenate(owner), np.concatenate(weight)
            for lo in range(0, len(x), CHUNK):
                np.add.at(total, who[lo : lo + CHUNK], self.run(x[lo : lo + CHUNK]) * w[lo : lo + CHUNK, None])

        for i, text in enumerate(texts):
            text = text.as_py() or ""
            if net is None or not any(map(str.isalpha, text)):
                continue
            data = text.encode("utf-8", "surrogatepass")
            letters[i], size[i] = True, len(data)
            x = windows_of(data)
            held.append(x)
            owner.append(np.full(len(x), i))
            w = np.full(len(x), float(LENGTH))
            w[-1] = len(data) - LENGTH * (len(x) - 1)
            weight.append(w)
            n += len(x)
            if n >= 4096:
                flush()
                held, owner, weight, n = [], [], [], 0
        if n:
            flush()
        names = [net.classes[b] if ok else UNKNOWN for b, ok in zip(total.argmax(1).tolist(), letters.tolist(), strict=True)]
        return names, np.clip(np.where(letters, total.max(1) / np.maximum(size, 1), 0.0), 0.0, 1.0)


def _identify(net: ByteNet | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        predict = Predictor(net)
        for batch in batches:
            names, score = predict(batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(names, pa.string()), pa.array(score)], names=["doc_id", "held_out", "lang_pred", "score"])

    return run


def _keep(net: ByteNet | None, text_at: int, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        predict = Predictor(net)
        for batch in batches:
            names, score = predict(batch.column(text_at))
            yield batch.filter(pa.array([n != UNKNOWN and s >= least for n, s in zip(names, score.tolist(), strict=True)], pa.bool_()))

    return run


def keep_identified(docs: DataFrame, net: ByteNet | None, least: float = 0.35) -> DataFrame:
    """The documents with a language, all columns; those with no letter or a score below ``least`` go."""
    return docs.mapInArrow(_keep(net, docs.columns.index("text"), least), docs.schema)


def identify(docs: DataFrame, net: ByteNet | None) -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred, score.

    Every window of a text counts. Null texts and those without a letter are ``und`` with score 0,
    and so is all if no labelled row was there to learn from; a null id counts as the empty
    text for held_out; other columns are ignored; repeated rows each get a row.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", held_out(F.col("doc_id")).alias("held_out"))
    return rows.mapInArrow(_identify(net), "doc_id long, held_out boolean, lang_pred string, score double")
