"""Toxicity: a bidirectional gated recurrent network with attention pooling, trained here in numpy.

Input of each step is a word: an embedding of the whole word (hashed) beside the mean
embedding of its character n-grams (hashed UTF-8 bytes), so unseen forms of a stem
still say something. A forward and a backward gated recurrent unit read windows of
``WINDOW`` words that start every ``STRIDE`` words; attention over their states gives
a window's logit. A document's score is that of its worst window, and every window of
the whole text is scored.

Training uses at most ``SAMPLE`` labelled documents of each label (by hash of doc_id,
texts up to ``SAMPLE_CHARS`` characters: less than 100 MB on the driver), with labels only of rows whose
crc32(doc_id) mod 5 is not 0. Which window makes a labelled document toxic is not
known; the one whose n-grams are most lopsided between the labels stands for it. The
logit that best parts the sampled documents becomes score 0.5.

Defined cases: null and empty texts, and texts of white space, score 0; without labels
of both kinds every score is 0; a null doc_id counts as held out; repeated rows
repeat; a doc_id that rows repeat is learnt from once; extra columns are ignored.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate.llm.tokens import let_go, slices
from mlcurate.session import prepare

WINDOW, STRIDE = 48, 40
SAMPLE, SAMPLE_CHARS = 1500, 30_000
WORD_ROWS, GRAM_ROWS, WORD_DIM, GRAM_DIM, HIDDEN, ATTEND = 1 << 13, 1 << 15, 8, 8, 8, 8
GRAMS = (3, 5, 8)
EPOCHS, STEPS, BATCH, RATE = 8, 400, 64, 0.01  # STEPS: at least so many, by more epochs where data are few
_MAX_WORDS = 150_000
_MARKS = re.compile(r"[\W_]+")


def words_of(text: str | None) -> list[str]:
    """Chunks between white space, lower-cased; marks are dropped when a chunk is looked up."""
    return (text or "").lower().split()


def features(words: list[str]) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    """Row of each word's own embedding; rows of its n-grams, one per byte and length, word after word; bytes of each word."""
    raw = [b"<" + _MARKS.sub("", w).encode() + b">" for w in words]
    own = np.array([zlib.crc32(r) for r in raw], np.int64) & (WORD_ROWS - 1)
    lens = np.array([len(r) for r in raw], np.int64)
    a = np.frombuffer(b"".join(raw), np.uint8)
    left = np.repeat(np.cumsum(lens), lens) - np.arange(len(a))  # bytes from here to the word's end
    a = np.concatenate([a, np.zeros(max(GRAMS), np.uint8)]).astype(np.uint32)
    ids = []
    for n in GRAMS:
        h = np.full(len(left), n, np.uint32)
        for k in range(n):
            h = (h ^ (a[k : len(left) + k] * (left > k))) * np.uint32(0x01000193)
            h ^= h >> np.uint32(15)
        ids.append((h & np.uint32(GRAM_ROWS - 1)).astype(np.int32))
    return own, ids, lens


def _sigmoid(x):
    return np.float32(0.5) * (np.tanh(np.float32(0.5) * x) + np.float32(1))


class Network:
    """Parameters and passes. Arrays are float32; steps run over the first axis of time."""

    def __init__(self, seed: int = 7):
        r = np.random.default_rng(seed)
        normal = lambda *s, scale=0.1: (r.standard_normal(s) * scale).astype(np.float32)
        d = WORD_DIM + GRAM_DIM
        self.p = {"word": normal(WORD_ROWS, WORD_DIM), "gram": normal(GRAM_ROWS, GRAM_DIM), "att": normal(2 * HIDDEN, ATTEND, scale=0.3), "att_b": normal(ATTEND), "att_v": normal(ATTEND, scale=0.5), "out": normal(2 * HIDDEN, scale=0.3), "out_b": np.zeros(1, np.float32)}
        for way in "fb":
            self.p |= {f"x{way}": normal(d, 3 * HIDDEN, scale=0.3), f"b{way}": np.zeros(3 * HIDDEN, np.float32), f"h{way}": normal(HIDDEN, 3 * HIDDEN, scale=0.3)}

    def embed(self, own: np.ndarray, ids: list[np.ndarray], lens: np.ndarray) -> np.ndarray:
        begin = np.cumsum(lens) - lens
        grams = sum(np.add.reduceat(self.p["gram"][i], begin, 0) for i in ids)
        return np.concatenate([self.p["word"][own], grams / lens[:, None].astype(np.float32)], 1)

    def project(self, x: np.ndarray) -> np.ndarray:
        """What the words bring to the gates of both directions."""
        return np.concatenate([x @ self.p[f"x{w}"] + self.p[f"b{w}"] for w in "fb"], 1)

    def _run(self, way: str, px: np.ndarray, real: np.ndarray, keep: list | None):
        """States of one direction, time first; px: time, batch, gates."""
        t, n = px.shape[:2]
        u, h, out = self.p[f"h{way}"], np.zeros((n, HIDDEN), np.float32), np.empty((t, n, HIDDEN), np.float32)
        for k in range(t) if way == "f" else range(t - 1, -1, -1):
            hu = h @ u
            zr = _sigmoid(px[k, :, : 2 * HIDDEN] + hu[:, : 2 * HIDDEN])
            z, r = zr[:, :HIDDEN], zr[:, HIDDEN:]
            c = np.tanh(px[k, :, 2 * HIDDEN :] + r * hu[:, 2 * HIDDEN :])
            new = c + z * (h - c)
            if way == "b":
                new *= real[k]
            if keep is not None:
                keep.append((k, h, z, r, c, hu[:, 2 * HIDDEN :]))
            out[k] = h = new
        return out

    def logits(self, px: np.ndarray, real: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """px: time, batch, gates of both directions; real: time, batch, 1."""
        g = 3 * HIDDEN
        kf, kb = ([], []) if keep is not None else (None, None)
        h = np.concatenate([self._run("f", px[..., :g], real, kf), self._run("b", px[..., g:], real, kb)], 2)
        t = np.tanh(h @ self.p["att"] + self.p["att_b"])
        e = np.where(real[..., 0] > 0, t @ self.p["att_v"], np.float32(-1e9))
        a = np.exp(e - e.max(0))
        a /= a.sum(0)
        pooled = (a[..., None] * h).sum(0)
        if keep is not None:
            keep |= {"f": kf, "b": kb, "h": h, "t": t, "a": a, "pooled": pooled}
        return pooled @ self.p["out"] + self.p["out_b"][0]

    def gradients(self, px, real, want):
        """Of the mean cross-entropy: parameters, and px."""
        keep: dict = {}
        y = self.logits(px, real, keep)
        d = (_sigmoid(y) - want) / len(want)
        p, h, a, t = self.p, keep["h"], keep["a"], keep["t"]
        g = {"out": keep["pooled"].T @ d, "out_b": np.array([d.sum()], np.float32)}
        dp = d[:, None] * p["out"]
        da = (h * dp).sum(2)
        de = a * (da - (a * da).sum(0))
        dt = de[..., None] * p["att_v"] * (1 - t * t)
        g |= {"att_v": (de[..., None] * t).sum((0, 1)), "att_b": dt.sum((0, 1)), "att": np.einsum("tni,tnj->ij", h, dt)}
        dh = a[..., None] * dp + dt @ p["att"].T
        dpx = np.zeros_like(px)
        gates = 3 * HIDDEN
        for way, off, hid in (("f", 0, slice(0, HIDDEN)), ("b", gates, slice(HIDDEN, 2 * HIDDEN))):
            u, gu = p[f"h{way}"], np.zeros_like(p[f"h{way}"])
            back = np.zeros((px.shape[1], HIDDEN), np.float32)
            for k, before, z, r, c, hn in reversed(keep[way]):
                s = dh[k, :, hid] + back
                if way == "b":
                    s = s * real[k]
                dc = s * (1 - z) * (1 - c * c)
                dg = np.concatenate([s * (before - c) * z * (1 - z), dc * hn * r * (1 - r), dc], 1)
                dpx[k, :, off : off + gates] = dg
                du = dg.copy()
                du[:, 2 * HIDDEN :] *= r
                gu += before.T @ du
                back = s * z + du @ u.T
            g[f"h{way}"] = gu
        return g, dpx, y


def windows(n: int) -> np.ndarray:
    """Where windows begin in a text of ``n`` words: the last one reaches its end."""
    return np.arange(0, max(n - WINDOW + STRIDE, 1), STRIDE)


def _matrix(rows: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Word rows of windows as (time, window), and which are real."""
    m = np.full((len(rows), WINDOW), -1, np.int64)
    for i, r in enumerate(rows):
        m[i, : len(r)] = r
    real = (m >= 0).T[..., None].astype(np.float32)
    return np.maximum(m, 0).T, real


def _keys(word: str) -> tuple[str, ...]:
    w = _MARKS.sub("", word)
    return (w, w[:5] + "*", w[:8] + "*")


def _lopsided(texts: list[list[str]], labels: np.ndarray) -> dict[str, float]:
    """Log odds of words and of their beginnings between labels, by documents; only of those seen in toxic ones."""
    toxic: dict[str, int] = {}
    for ws in (t for t, y in zip(texts, labels, strict=True) if y):
        for k in {k for x in set(ws) for k in _keys(x)}:
            toxic[k] = toxic.get(k, 0) + 1
    toxic = {k: n for k, n in toxic.items() if n > 1}
    clean = dict.fromkeys(toxic, 0)
    for ws in (t for t, y in zip(texts, labels, strict=True) if not y):
        for k in {k for x in set(ws) for k in _keys(x) if k in clean}:
            clean[k] += 1
    n1, n0 = max(int(labels.sum()), 1), max(int((1 - labels).sum()), 1)
    return {k: np.log((n + 0.1) / n1) - np.log((clean[k] + 0.1) / n0) for k, n in toxic.items()}


def _summed(rows: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """Sums of value rows by target row."""
    return np.stack([np.bincount(rows, values[:, j], n) for j in range(values.shape[1])], 1).astype(np.float32)


def train(texts: list[str], labels: list[int], seed: int = 7) -> Network | None:
    """Fit on whole labelled texts."""
    y = np.array(labels, np.int64)
    if len(set(labels)) < 2:
        return None
    rng = np.random.default_rng(seed)
    net = Network(seed)

    def pick(worth):
        """Windows to learn from: each document's most telling one; of clean documents two more at random. Only their words are held."""
        shown, want, vocab = [], [], {}
        for i, (t, label) in enumerate(zip(texts, y, strict=True)):
            ws = words_of(t)
            if ws:
                begins = windows(len(ws))
                for k in {worth(i, ws, begins)} | (set() if label else set(rng.integers(0, len(begins), 2).tolist())):
                    shown.append(np.array([vocab.setdefault(w, len(vocab)) for w in ws[begins[k] : begins[k] + WINDOW]], np.int64))
                    want.append(label)
        return shown, np.array(want, np.float32), features(list(vocab))

    odds = _lopsided([words_of(t) for t in texts], y)
    worth = lambda ws: np.array([max(odds.get(k, 0.0) for k in _keys(w)) for w in ws])
    shown, want, (own, ids, lens) = pick(lambda i, ws, begins: int(np.argmax([v[b : b + WINDOW].max() for v in [worth(ws)] for b in begins])))
    del odds
    ends = np.cumsum(lens)
    m1, m2 = {k: np.zeros_like(v) for k, v in net.p.items()}, {k: np.zeros_like(v) for k, v in net.p.items()}
    step, epochs = 0, max(EPOCHS, -(-STEPS * BATCH // max(len(shown), 1)))
    for epoch in range(epochs):
        if epoch == epochs // 2:  # by now the network tells better than the odds which windows matter
            seen = Scorer(net, 60_000).by_text(texts, lambda x: int(np.argmax(x)) if len(x) else 0)
            shown, want, (own, ids, lens) = pick(lambda i, ws, begins: seen[i])  # noqa: B023
            ends = np.cumsum(lens)
        order = rng.permutation(len(shown))
        for at in range(0, len(order), BATCH):
            part = order[at : at + BATCH]
            m, real = _matrix([shown[k] for k in part])
            used, inverse = np.unique(m, return_inverse=True)
            inverse = inverse.reshape(-1)
            n = lens[used]
            place = np.repeat(ends[used] - np.cumsum(n), n) + np.arange(n.sum())
            gi = [x[place] for x in ids]
            x = net.embed(own[used], gi, n)
            hide = rng.random(len(x)) < 0.5  # half of the words show their n-grams only, so words are not learnt by heart
            x[hide, :WORD_DIM] = 0
            px = net.project(x)[inverse.reshape(m.shape)]
            g, dpx, _ = net.gradients(px, real, want[part])
            flat = _summed(inverse, dpx.reshape(-1, dpx.shape[2]), len(used))
            dx = np.zeros_like(x)
            for w, off in (("f", 0), ("b", 3 * HIDDEN)):
                d = flat[:, off : off + 3 * HIDDEN]
                g[f"x{w}"], g[f"b{w}"] = x.T @ d, d.sum(0)
                dx += d @ net.p[f"x{w}"].T
            dx[hide, :WORD_DIM] = 0
            g["word"] = _summed(own[used], dx[:, :WORD_DIM], WORD_ROWS)
            each = np.repeat(dx[:, WORD_DIM:] / n[:, None].astype(np.float32), n, 0)
            g["gram"] = sum(_summed(i, each, GRAM_ROWS) for i in gi)
            step += 1
            rate = np.float32(RATE * (1 - epoch / (epochs + 1)))
            for k, v in net.p.items():
                m1[k] += np.float32(0.1) * (g[k] - m1[k])
                m2[k] += np.float32(0.01) * (g[k] * g[k] - m2[k])
                v -= rate * (m1[k] / (1 - 0.9**step)) / (np.sqrt(m2[k] / (1 - 0.99**step)) + np.float32(1e-6))
    logit = Scorer(net, 60_000).logits(texts)
    cuts = np.unique(logit[np.isfinite(logit)])
    mids = np.concatenate([(cuts[1:] + cuts[:-1]) / 2, [0.0]]) if len(cuts) > 1 else np.zeros(1)
    up, down = np.sort(logit[y == 1]), np.sort(logit[y == 0])
    wrong = np.searchsorted(up, mids) + len(down) - np.searchsorted(down, mids)
    best = mids[wrong == wrong.min()]
    net.p["out_b"] = net.p["out_b"] - np.float32(best[np.argmin(np.abs(best - np.median(best)))])
    return net


class Scorer:
    """Scores whole texts; projections of known words are kept."""

    def __init__(self, net: Network, most_words: int = _MAX_WORDS):
        self.net, self.index, self.most_words = net, {}, most_words
        self.table = np.zeros((1 << 12, 6 * HIDDEN), np.float32)

    def _rows(self, flat: list[str]) -> np.ndarray:
        new = set(flat).difference(self.index)
        if new:
            if len(self.index) + len(new) > self.most_words:
                self.index.clear()
                new = set(flat)
            new = list(new)
            at = len(self.index)
            if at + len(new) > len(self.table):
                more = max(len(self.table) // 4, at + len(new) - len(self.table))
                self.table = np.concatenate([self.table, np.zeros((more, 6 * HIDDEN), np.float32)])
            for i in range(0, len(new), 20_000):
                part = new[i : i + 20_000]
                self.table[at + i : at + i + len(part)] = self.net.project(self.net.embed(*features(part)))
            self.index.update(zip(new, range(at, at + len(new)), strict=True))
        return np.fromiter(map(self.index.__getitem__, flat), np.int64, len(flat))

    def window_logits(self, texts: list[str | None], most: int = 2048) -> list[np.ndarray]:
        """Logits of all windows of each text."""
        cut = [words_of(t) for t in texts]
        flat = self._rows([w for ws in cut for w in ws])
        n = np.array([len(ws) for ws in cut], np.int64)
        each = [windows(k) if k else np.zeros(0, np.int64) for k in n.tolist()]
        count = np.array([len(b) for b in each], np.int64)
        start = np.repeat(np.cumsum(n) - n, count)
        local = np.concatenate(each) if each else np.zeros(0, np.int64)
        begins, lens = local + start, np.minimum(WINDOW, np.repeat(n, count) - local)
        out = np.zeros(len(begins))
        order = np.argsort(-lens, kind="stable")  # full windows together, short ones in shorter batches
        step = np.arange(WINDOW)
        for i in range(0, len(order), most):
            part = order[i : i + most]
            t = int(lens[part].max())
            at = begins[part] + step[:t, None]
            real = (step[:t, None] < lens[part]).astype(np.float32)[..., None]
            out[part] = self.net.logits(self.table[flat[np.minimum(at, len(flat) - 1)]], real)
        return np.split(out, np.cumsum(count)[:-1]) if len(count) else []

    def by_text(self, texts: list[str | None], what) -> list:
        """``what`` of the window logits of each text, a bounded number of texts at a time."""
        return [what(x) for i, j in slices(texts, 500_000) for x in self.window_logits(texts[i:j])]

    def logits(self, texts: list[str | None]) -> np.ndarray:
        """Worst window's logit of each text; minus infinity without words."""
        return np.array(self.by_text(texts, lambda x: x.max() if len(x) else -np.inf))


def sample(docs: DataFrame, labels: DataFrame, n: int = SAMPLE) -> tuple[list[str], list[int]]:
    """At most ``n`` training texts of each label, one of each doc_id (the first in order where rows repeat it)."""
    own = labels.select(F.col("doc_id").cast("long"), F.col("toxic").cast("int")).where("doc_id is not null and toxic in (0, 1)")
    own = own.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    picked = [own.where(F.col("toxic") == k).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n) for k in (0, 1)]
    few = F.broadcast(picked[0].union(picked[1]))  # 2 n rows at most
    rows = docs.select(F.col("doc_id").cast("long"), "text").where((F.length("text") > 0) & (F.length("text") <= SAMPLE_CHARS)).join(few, "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text")).collect()
    rows.sort(key=lambda r: (r.doc_id, r.text))
    return [r.text for r in rows], [r.toxic for r in rows]


def fit(docs: DataFrame, labels: DataFrame, n: int = SAMPLE) -> Network | None:
    return train(*sample(docs, labels, n))


def _scored(docs: DataFrame, net: Network | None, keep: tuple[str, ...]) -> DataFrame:
    """``keep`` columns as k_<name>, doc_id and __score."""
    spark = prepare(docs.sparkSession)
    # the text goes to the workers once, also where it is kept
    part = docs.select(*[F.col(c).alias(f"k_{c}") for c in keep], F.col("doc_id").cast("long").alias("doc_id"), *([] if "text" in keep else [F.col("text").alias("k_text")]))
    fields = [f for f in part.schema.fields if f.name != "k_text" or "text" in keep]
    names = [f.name for f in fields]
    if net is None:
        return part.select(*names, F.lit(0.0).alias("__score"))
    model = spark.sparkContext.broadcast(net)  # some hundred KB

    def run(batches):
        import pyarrow as pa

        let_go()
        s = Scorer(model.value)
        for b in batches:
            x = s.logits(b.column("k_text").to_pylist())
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in names], pa.array(0.5 * (np.tanh(0.5 * np.clip(x, -80, 80)) + 1) * np.isfinite(x), pa.float64())], [*names, "__score"])
        del s
        let_go()

    from pyspark.sql.types import DoubleType, StructType

    return part.mapInArrow(run, StructType(fields).add("__score", DoubleType()))


def score(docs: DataFrame, net: Network | None) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document."""
    held = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 5 == 0
    return _scored(docs, net, ()).select("doc_id", held.alias("held_out"), F.col("__score").alias("score"), (F.col("__score") >= 0.5).cast("int").alias("predicted"))


def clean(docs: DataFrame, net: Network | None) -> DataFrame:
    """``docs`` without the documents that score 0.5 or more."""
    names = docs.columns
    x = _scored(docs.select(*names), net, tuple(c for c in names if c != "doc_id")).where("__score < 0.5")
    return x.select(*[F.col("doc_id") if c == "doc_id" else F.col(f"k_{c}").alias(c) for c in names])
