"""Language identification by string kernels.

The kernel of two texts is the number of byte runs of length one to four that both contain (a blended spectrum of
presence), normalised by their own counts. Nyström landmarks turn it into features for one-versus-rest kernel
ridge regression. As the scores are linear in a text's presence vector, the landmarks and the regression fold
into one matrix of a row per hashed run and a column per language; a batch of whole texts is then scored by one
sparse matrix product. Its entries are rounded to a grid on which double sums are exact, so scores don't depend
on how texts are batched.

The scores only say which of the learned languages is nearest. Whether a text is in any of them is told by its
support: the share of its runs that training texts have, with a bound set on texts held out of the training.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from factbench.llm.common import settles, tidy

ORDERS, BITS = 4, 18
_SPREAD = np.array([2654435761, 2246822519, 3266489917, 668265263], np.uint32)
_LETTERS = bytes(c if chr(c).isalpha() or c > 127 else 32 for c in range(256))
UNKNOWN = "und"


def has_letter(text: str) -> Column:
    return F.coalesce(F.col(text).rlike(r"\p{L}"), F.lit(False))


class Presence:
    """Distinct hashed byte runs of whole texts; keeps one table of flags."""

    def __init__(self):
        self.flags = np.zeros(1 << BITS, bool)

    def __call__(self, text: str) -> np.ndarray:
        letters = b" ".join([b"", *text.lower().encode("utf-8", "replace").translate(_LETTERS).split(), b""])
        code = data = np.frombuffer(letters, np.uint8).astype(np.uint32)
        for order in range(ORDERS):
            if order:
                code = (code[:-1] << np.uint32(8)) | data[order:]
            self.flags[(code * _SPREAD[order]) >> np.uint32(32 - BITS)] = True
        found = np.flatnonzero(self.flags)
        self.flags[found] = False
        return found.astype(np.int32)


@dataclass
class LanguageModel:
    languages: list[str]
    weights: np.ndarray  # (1 << BITS) x languages
    bias: np.ndarray
    known: np.ndarray | None = None  # a flag per hashed run that training texts have
    least_support: float = 0.0

    def support(self, sets: list[np.ndarray]) -> np.ndarray:
        """The share of each text's runs that training texts have; 1 for all where none were recorded."""
        return np.array([1.0 if self.known is None else self.known[s].mean() for s in sets])

    def scores(self, sets: list[np.ndarray]) -> np.ndarray:
        """A row per text, a column per language: the sparse presence matrix times the weights, normalised."""
        lengths = np.array([len(s) for s in sets])
        sums = np.add.reduceat(self.weights[np.concatenate(sets)].astype(np.float64), np.r_[0, np.cumsum(lengths)[:-1]], axis=0)
        return sums / np.sqrt(lengths)[:, None] + self.bias


def _kernel(a: list[np.ndarray], b: list[np.ndarray]) -> np.ndarray:
    out = np.empty((len(a), len(b)))
    flags = np.zeros(1 << BITS, bool)
    for i, own in enumerate(a):
        flags[own] = True
        out[i] = [flags[s].sum() / np.sqrt(len(s) * len(own)) for s in b]
        flags[own] = False
    return out


def fit(marks: list[np.ndarray], k_nm: np.ndarray, labels: list[str], ridge: float = 1e-3) -> LanguageModel:
    """Kernel ridge regression on Nyström features: ``marks`` are the landmarks' sets, ``k_nm`` the kernel of every labelled text with each."""
    languages = sorted(set(labels))
    k_mm = _kernel(marks, marks)
    values, basis = np.linalg.eigh((k_mm + k_mm.T) / 2)
    good = values > 1e-8 * values[-1]
    root = basis[:, good] / np.sqrt(values[good])
    features = np.c_[k_nm @ root, np.ones(len(labels))]
    targets = np.where(np.array(labels)[:, None] == np.array(languages)[None, :], 1.0, -1.0)
    penalty = ridge * len(labels) * np.diag(np.r_[np.ones(int(good.sum())), 1e-6])
    solved = np.linalg.solve(features.T @ features + penalty, features.T @ targets)
    per_mark = root @ solved[:-1]
    weights = np.zeros((1 << BITS, len(languages)))
    for own, row in zip(marks, per_mark, strict=True):
        weights[own] += row / np.sqrt(len(own))
    grid = 2.0**20
    return LanguageModel(languages, (np.round(weights * grid) / grid).astype(np.float32), solved[-1])


HELD = 4  # every fourth text of a language is held out of the runs that set the bound


def _kernel_rows(marks):
    """(lang, turn, kernel): a text's kernel with every landmark."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        presence = Presence()
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part = batch.slice(at, 64)
                rows = _kernel([presence(t) for t in part.column(2).to_pylist()], marks.value)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array([r.tobytes() for r in rows], pa.binary())], names=["lang", "turn", "kernel"])

    return run


def _run_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(lang, held, counts): of a partition's texts, how many have each run, up to two; held-out texts apart."""
    presence, counts = Presence(), {}
    for batch in batches:
        for lang, turn, text in zip(*[c.to_pylist() for c in batch.columns], strict=True):
            own = counts.setdefault((lang, turn % HELD == HELD - 1), np.zeros(1 << BITS, np.uint8))
            found = presence(text)
            own[found] = np.minimum(own[found] + 1, 2)
    if counts:
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in counts]), pa.array([k[1] for k in counts]), pa.array([c.tobytes() for c in counts.values()], pa.binary())], names=["lang", "held", "counts"])


def _support_rows(known):
    """(whole, shuffled): the known share of a held-out text's runs, and of those of its characters in random order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        presence, flags = Presence(), known.value
        for batch in batches:
            texts = batch.column(2).to_pylist()
            mixed = ["".join(np.random.default_rng(len(t)).permutation(list(t))) for t in texts]
            yield pa.RecordBatch.from_arrays([pa.array([float(flags[presence(t)].mean()) for t in those], pa.float64()) for those in (texts, mixed)], names=["whole", "shuffled"])

    return run


def known_runs(tables: list[tuple[str, bool, np.ndarray]], sizes: dict[str, int], held: bool) -> np.ndarray:
    """Flags of the runs that two texts of one language have, or one text where a language has fewer than eight; with or without the ``held`` ones."""
    out = np.zeros(1 << BITS, bool)
    for lang in sizes:
        own = np.zeros(1 << BITS, np.int32)
        for c, h, counts in tables:
            if c == lang and (held or not h):
                own += counts
        out |= own >= (2 if sizes[lang] >= 8 else 1)
    return out


def support_bound(whole: np.ndarray, shuffled: np.ndarray, lost: float = 0.005, way: float = 0.4, fewest: int = 8) -> float:
    """A bound that lies ``way`` from the median of shuffled texts to what all but ``lost`` of the whole texts, or all but two, reach.

    Two, as ``lost`` of few texts is less than one, and a single text with a wrong label would set the bound. It errs to
    the side of keeping, as short texts with an address or a token have less support; a language whose runs the learned
    ones share is above it. Fewer than ``fewest`` held-out texts set no bound (0).
    """
    if len(whole) < fewest:
        return 0.0
    high, low = np.quantile(whole, max(lost, 2 / (len(whole) - 1))), np.median(shuffled)
    return float(min(high, low + way * (high - low)))


def sampled(labelled: DataFrame, key: str, text: str, lang: str, sample_rows: int) -> DataFrame:
    """(lang, turn, text): for each language its share of ``sample_rows``, those of least hash of the id; ``turn`` numbers them.

    Only rows whose hash is below a bound for about four times that many are ranked, so no task sees more than a
    small multiple of the sample whatever the table's size. Of more labels than ``sample_rows``, the most frequent count.
    """
    counts = labelled.groupBy(F.col(lang).alias("_lang")).agg(F.count(F.lit(1)).alias("_n")).orderBy(F.desc("_n"), "_lang").limit(sample_rows)
    share = F.greatest(F.lit(1), F.floor(F.lit(sample_rows) / F.count(F.lit(1)).over(Window.partitionBy()))).cast("int")
    # hashes spread evenly over 64 bits; four times the share and 64 rows fall short of the share once in very many runs
    bound = F.least(F.lit(1.0), (4 * F.col("_share") + 64) / F.col("_n")) * F.lit(2.0**64) - F.lit(2.0**63)
    bounds = counts.withColumn("_share", share).select("_lang", "_share", bound.alias("_bound"))
    draw = F.xxhash64(key)
    near = labelled.join(F.broadcast(bounds), F.col(lang) == F.col("_lang")).filter(draw.cast("double") <= F.col("_bound"))
    order = Window.partitionBy("_lang").orderBy("_draw", "_id", "_text")
    ranked = near.select("_lang", "_share", draw.alias("_draw"), F.col(key).alias("_id"), F.col(text).alias("_text")).withColumn("turn", F.row_number().over(order) - 1)
    return ranked.filter(F.col("turn") < F.col("_share")).select(F.col("_lang").alias("lang"), "turn", F.col("_text").alias("text"))


@settles
def _sample_table(labelled: DataFrame, key: str, text: str, lang: str, sample_rows: int) -> DataFrame:
    return sampled(labelled, key, text, lang, sample_rows)


def train(docs: DataFrame, learn: Column, key: str = "doc_id", text: str = "text", lang: str = "lang", sample_rows: int = 2048, support: bool = False, landmarks: int = 128, ridge: float = 1e-3) -> LanguageModel | None:
    """Fit on at most ``sample_rows`` whole texts with a letter among the rows where ``learn`` holds; with ``support``, learn its bound too.

    Every language gets the same share of the bound (one row at least), filled in the order of a hash of the id;
    landmarks are taken from all languages in turn. The driver holds the landmarks' run sets and the kernel
    matrix alone; texts and all other sets stay in the tasks. Null keys, labels and texts, and texts without a letter, are
    left out. None if there is nothing to learn from.
    """
    labelled = docs.filter(learn & F.col(lang).isNotNull() & F.col(key).isNotNull()).filter(has_letter(text))
    sample = _sample_table(labelled, key, text, lang, sample_rows)
    context = docs.sparkSession.sparkContext
    chosen = sample.orderBy("turn", "lang").limit(landmarks)
    found = chosen.mapInArrow(_presence_rows, "lang string, turn int, found binary").toArrow()
    order = sorted(range(found.num_rows), key=lambda i: (found["turn"][i].as_py(), found["lang"][i].as_py()))
    marks = [np.frombuffer(found["found"][i].as_py(), np.int32) for i in order]
    if not marks:
        return None
    shared = context.broadcast(marks)
    rows = sample.mapInArrow(_kernel_rows(shared), "lang string, turn int, kernel binary").toArrow()
    pairs = sorted(zip(*[rows[c].to_pylist() for c in ("lang", "turn", "kernel")], strict=True))
    labels = [c for c, *_ in pairs]
    model = fit(marks, np.stack([np.frombuffer(k) for *_, k in pairs]), labels, ridge)
    if support:
        sizes = {c: labels.count(c) for c in model.languages}
        told = sample.coalesce(8).mapInArrow(_run_counts, "lang string, held boolean, counts binary").toArrow()
        tables = [(c, h, np.frombuffer(b, np.uint8)) for c, h, b in zip(*[told[c].to_pylist() for c in ("lang", "held", "counts")], strict=True)]
        kept = context.broadcast(known_runs(tables, {c: n - n // HELD for c, n in sizes.items()}, held=False))
        tested = sample.filter(F.col("turn") % HELD == HELD - 1).mapInArrow(_support_rows(kept), "whole double, shuffled double").toArrow()
        model.known, model.least_support = known_runs(tables, sizes, held=True), support_bound(*(tested[c].to_numpy() for c in ("whole", "shuffled")))
    return model


def _presence_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    presence = Presence()
    for batch in batches:
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([presence(t).tobytes() for t in batch.column(2).to_pylist()], pa.binary())], names=["lang", "turn", "found"])


def predict(docs: DataFrame, model: LanguageModel | None, text: str = "text", pred: str = "lang_pred", score: str = "score", carry: list[str] | None = None, support: str | None = None) -> DataFrame:
    """Add the predicted language of every whole text, and the winner's score scaled to 0..1; its support, if a column is named.

    Null texts, and texts without a letter, are ``und`` with score 0, as is everything without a model. Other
    columns are carried along (only those in ``carry``, if given); one with the name of a new column gives way to it. Repeated rows get
    equal results; an empty table gives an empty table.
    """
    names = [c for c in (docs.columns if carry is None else carry) if c not in (pred, score, support)]
    if model is None:
        return docs.select(*names, F.lit(UNKNOWN).alias(pred), F.lit(0.0).alias(score), *([F.lit(0.0).alias(support)] if support else []))
    shared = docs.sparkSession.sparkContext.broadcast(model)
    fields = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, presence = shared.value, Presence()
        tidy()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = part.column(part.num_columns - 1).to_pylist()
                best, most, backed = np.full(len(texts), -1), np.zeros(len(texts)), np.zeros(len(texts))
                some = [i for i, t in enumerate(texts) if t is not None]
                if some:
                    sets = [presence(texts[i]) for i in some]
                    scores = known.scores(sets)
                    best[some] = scores.argmax(axis=1)
                    most[some] = np.clip((1 + scores.max(axis=1)) / 2, 0, 1)
                    if support:
                        backed[some] = known.support(sets)
                yield pa.RecordBatch.from_arrays(
                    [*part.columns[: len(names)], pa.array([known.languages[i] if i >= 0 else UNKNOWN for i in best.tolist()]), pa.array(most), *([pa.array(backed)] if support else [])],
                    names=[*names, pred, score, *([support] if support else [])],
                )
            del batch
            tidy()

    return docs.select(*names, F.when(has_letter(text), F.col(text)).alias("_letters")).mapInArrow(run, f"{fields}, {pred} string, {score} double" + (f", {support} double" if support else ""))
