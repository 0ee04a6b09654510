"""The layered protocol: two active-learning loops with back-propagation, for many runs at once.

Candidates are compared where they come up and never written as a whole: one pass makes their histogram, a second one writes the
band of similarities that runs are uncertain of, with some room for their thresholds to move, sorted by similarity; no round writes it
again, and a range is added when a run leaves it.  A non-reviewed pair's label is
``sim >= t``, so reclassifying all of them is a new scalar, and their part of F1 comes from a histogram of at most 1,001
bins.  A round reads the uncertain band (a range of similarities) for all runs together, draws each run's batch, lets the
owners encode the drawn pairs that no run had before, and then advances every run by one grouped task that holds the run's
reviewed pairs (bounded by its budget), its forest and its threshold.  The driver sees one row a run.
"""

from __future__ import annotations

import hashlib
import pickle
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkveil.functions import bits
from linkveil.operators import block, classify, compare, encode, measures, owner, pairwise, sampling
from linkveil.operators.forest import FEATURES, EvolvingForest, matrix, weight
from linkveil.session import durable, released, sent, stored
from linkveil.sources.registry import ATTRIBUTES

STEP = 0.001
#: Between a scenario and a run in a run's id.
MARK = ":"
STATE_PARTS = 256
#: Pairs of the uncertain band that may be written beyond what the runs' thresholds ask for.
BAND_ROWS = 2_000_000


@dataclass(frozen=True)
class Schedule:
    """Batches of the upper loop, small ones first, and of the lower loop (two a small batch)."""

    small: int = 100
    n_small: int = 5
    big: int = 1000
    n_big: int = 4
    budget: int = 100

    @property
    def lower(self) -> int:
        return self.budget // 10

    @classmethod
    def scaled(cls, n_records: int, budget: int | None = None, part: float = 0.2) -> Schedule:
        """The published ratios for sources of ``n_records``: 100 and 1,000 pairs at 50,000, a tenth at 5,000; ``part`` of the warm-up is human."""
        scale = min(1.0, max(0.04, n_records / 50_000))
        small = max(4, round(100 * scale))
        return cls(small, 5, max(2 * small, round(1000 * scale)) if scale > 0.05 else 2 * small, 4, budget if budget is not None else max(10, round(5 * small * part)))


@dataclass(frozen=True)
class Settings:
    """One scenario; each of its runs has a start and a repetition.

    ``ask_more`` raises batches by the response rate, so that as many pairs come back as the schedule says; ``human`` is
    ``simulated`` or ``table`` (labels that someone else gives); ``encoder`` names a member of ENCODERS; without ``key_seed``
    pair keys are random."""

    schedule: Schedule = field(default_factory=Schedule)
    err: float = 0.2
    offsets: tuple[float, ...] = tuple(round(-0.05 + 0.01 * i, 2) for i in range(11))
    repetitions: int = 3
    p_limit: float = 0.8
    buckets: int = 10
    below: float = 0.05
    above: float = 0.1
    max_drift: float = 0.10
    max_step: float = 0.02
    measure: str = "accuracy"
    sampler: str = "bucketed"
    attribute_model: str = "forest"
    pretrained: bytes | None = None
    propagate: str = "per_lower_batch"
    update_top: bool = True
    replace_labels: bool = True
    layers: tuple[str, ...] = ("top", "attr", "plain")
    reply_rate: float = 1.0
    ask_more: bool = False
    human: str = "simulated"
    encoder: str = "filters"
    key_seed: int | None = None
    label_source: str = "current"
    seed: int = 1


@dataclass
class Layer:
    """Records with filters and block digests, and their rows dealt out by block.  Pairs grow with the square of the records: they are
    made and compared in the tasks, each time anew, and never written."""

    keyed: DataFrame
    large: DataFrame
    n_records: int
    m: int
    records: DataFrame
    encoded: Callable[[DataFrame], DataFrame]
    many: int = pairwise.MANY

    def dealt(self, key_no: int | None = None, part: int = 0, parts: int = 1) -> DataFrame:
        """All rows, or those of a pass, for which only its records are encoded."""
        if key_no is None:
            return pairwise.dealt(self.keyed, self.large, self.m, self.n_records)
        keyed = self.encoded(pairwise.of_pass(self.records, (key_no, part, parts)))
        return pairwise.dealt(keyed, self.large, self.m, -(-self.n_records // parts), key_no)

    def passes(self) -> list[tuple]:
        return [one or () for one in pairwise.passes(self.n_records, self.m, self.many)]

    def gathered(self, make: Callable[[tuple], DataFrame], write: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
        """The union of what ``make`` takes from each pass.  It is written pass by pass, and a pass's shuffle is let go before the next
        one, so that only a part of the filters lies on disk at a time."""
        found = None
        for one in self.passes():
            each = (write or durable)(make(one))
            released(each.sparkSession)
            found = each if found is None else found.unionByName(each)
        return found

    def pairs(self, lo: float | None = None, hi: float | None = None, floor: float | None = None, one: tuple = ()) -> DataFrame:
        """Compared pairs (pair_id, left_id, right_id, l_ones, r_ones, common, sim, truth), of a pass or of all; with limits those with lo < sim < hi, or sim >= floor."""
        found = pairwise.pairs(self.dealt(*one), self.m, lo, hi, floor)
        pair_id, sim = F.concat_ws("-", "left_id", "right_id").alias("pair_id"), compare.dice(F.col("common"), F.col("l_ones"), F.col("r_ones"))
        return found.select(pair_id, "left_id", "right_id", "l_ones", "r_ones", "common", sim.alias("sim"), "truth")

    def tally(self) -> DataFrame:
        """(sim, truth, n): numbers of pairs, counted where they come up, pass by pass."""
        if self.n_records < self.many:
            found = pairwise.tally(self.dealt(), self.m)
        else:
            found = self.gathered(lambda one: pairwise.tally(self.dealt(*one), self.m).groupBy("common", "ones", "truth").agg(F.sum("n").alias("n")))
        return found.select(F.try_divide(2.0 * F.col("common"), F.col("ones")).alias("sim"), "truth", "n")


@dataclass
class Prepared:
    """A data set after the batch matching of the top layer."""

    name: str
    records: DataFrame
    layer: Layer
    histogram: np.ndarray
    n_true: int
    t_best: float
    f1_best: float
    parameters: encode.Parameters
    features: DataFrame | None = None
    band: tuple[float, float, DataFrame] | None = None

    @property
    def filters(self) -> DataFrame:
        return self.layer.keyed

    @property
    def candidates(self) -> DataFrame:
        return self.layer.pairs()

    def within(self, lo: float, hi: float) -> DataFrame:
        """Candidates (pair_id, left_id, right_id, sim, truth) with lo < sim < hi.  They are written once, by sim within a file; when a wider
        range is asked for, what is missing is added.  All others are never written."""
        if self.band is None:
            self.band = lo, hi, self._written(lo, hi)
        low, high, found = self.band
        if lo < low:
            low, found = lo, found.unionByName(self._written(lo, np.nextafter(low, 2.0)))
        if hi > high:
            high, found = hi, found.unionByName(self._written(np.nextafter(high, -1.0), hi))
        self.band = low, high, found
        return found.where((F.col("sim") > lo) & (F.col("sim") < hi)).select(F.concat_ws("-", "left_id", "right_id").alias("pair_id"), "left_id", "right_id", "sim", "truth")

    def _written(self, lo: float, hi: float) -> DataFrame:
        lo, hi = float(lo), float(hi)
        return self.layer.gathered(lambda one: self.layer.pairs(lo, hi, one=one).select("left_id", "right_id", "sim", "truth").sortWithinPartitions("sim"), stored)

    def room(self, lo: float, hi: float, reach: tuple[float, float], rows: int | None = None) -> tuple[float, float]:
        """The range widened within ``reach``, on both sides in turn, as long as it has at most ``rows`` pairs or twice those asked for."""
        counts = self.histogram.sum(axis=1)
        within = lambda a, b: int(counts[max(0, int(a / STEP)) : max(0, int(b / STEP)) + 1].sum())
        most = max(BAND_ROWS if rows is None else rows, 2 * within(lo, hi))
        open_ = {0, 1}
        while open_:
            for side in sorted(open_):
                wider = (max(lo - 0.01, reach[0]), hi) if side == 0 else (lo, min(hi + 0.01, reach[1]))
                if wider[0] >= lo and wider[1] <= hi or within(*wider) > most:
                    open_.discard(side)
                else:
                    lo, hi = wider
        return lo, hi


def layer(records: DataFrame, p: encode.Parameters, hardening: str | None = None) -> Layer:
    """Encodes, blocks and deals out records, of which each has one row."""
    folded = hardening == "xor"
    return _layer(records, p, p.m // 2 if folded else p.m, lambda keyed: pairwise.filters(keyed, p, folded, ["keys"]))


def attribute_layer(records: DataFrame, p: encode.Parameters) -> Layer:
    """The same of attribute filters under the owners' key: ``pairwise.attribute_filters``."""
    return _layer(records, p, pairwise.attribute_bits(p), lambda keyed: pairwise.attribute_filters(keyed, p, ["keys"]))


def attribute_tally(records: DataFrame, p: encode.Parameters, weights: Mapping[str, float] = encode.WEIGHTS) -> DataFrame:
    """(sim, truth, n) for a histogram: numbers of pairs of the blocking by the attribute-only baseline's score, counted pass by pass."""
    found = attribute_layer(records, p)
    take = lambda one: pairwise.score_tally(found.dealt(*one), p, weights, STEP, measures.BORDER)
    if found.n_records < found.many:
        return take(())
    return found.gathered(lambda one: take(one).groupBy("sim", "truth").agg(F.sum("n").alias("n")))


def _layer(records: DataFrame, p: encode.Parameters, m: int, filters: Callable[[DataFrame], DataFrame]) -> Layer:
    n_records, records = records.count(), block.keys(records, p.key)
    large = pairwise.large_blocks(records.select("owner", "keys"))
    released(records.sparkSession)
    if n_records >= pairwise.MANY:  # values are short; a task whose filters pass its memory would write them twice
        records = records.drop("keys").repartition(-(-n_records // (pairwise.ROWS_A_TASK // len(block.KEYS))), "rec_id")
        records = block.keys(records, p.key)
    encoded = lambda keyed: filters(keyed).select("rec_id", "owner", *bits.names(m), "ones", "entity_id", "keys")
    return Layer(encoded(records), large, n_records, m, records, encoded)


def top_layer(records: DataFrame, p: encode.Parameters, hardening: str | None = None, floor: float | None = None) -> tuple[DataFrame, DataFrame]:
    """(filters, candidates): record filters with block digests, and compared pairs."""
    found = layer(records, p, hardening)
    return found.keyed, found.pairs(floor=floor)


def prepare(records: DataFrame, p: encode.Parameters, name: str = "", hardening: str | None = None) -> Prepared:
    """Batch matching, with truth for the evaluation: the pairs, their histogram, and the best threshold.  ``records`` are written already."""
    found = layer(records, p, hardening)
    counts = measures.histogram(found.tally(), step=STEP, weight="n")
    n_true = measures.true_pairs(records).count()
    table = np.zeros((int(1 / STEP) + 2, 2), dtype=np.int64)
    for row in counts.collect():  # 1,001 bins at most
        table[row["bin"]] = row["n_true"], row["n"] - row["n_true"]
    t, f = best_of(table, n_true)
    released(records.sparkSession)
    return Prepared(name, records, found, table, n_true, t, f, p)


def counts_at(table: np.ndarray, t: float) -> tuple[int, int]:
    """True and false pairs at or over a threshold of the grid."""
    return tuple(int(x) for x in table[max(0, round(t / STEP)) :].sum(axis=0))


def best_of(table: np.ndarray, n_true: int) -> tuple[float, float]:
    above = table[::-1].cumsum(axis=0)[::-1]
    scores = np.round(2 * above[:, 0] / np.maximum(above[:, 0] + above[:, 1] + n_true, 1), 9)
    k = int(np.argmax(scores))
    return round(k * STEP, 9), float(scores[k])


def f1_of(tp: int, fp: int, n_true: int) -> float:
    return 2 * tp / max(1, tp + fp + n_true)


def _lot(seed: object, pair_id: str) -> str:
    return hashlib.md5(f"{seed}|{pair_id}".encode()).hexdigest()


def _uniform(pair_id: str, tag: str) -> float:
    return int(hashlib.md5(f"{pair_id}|{tag}".encode()).hexdigest()[:8], 16) / 4294967296.0


def ramp(sim: np.ndarray, t: float, s: Settings) -> np.ndarray:
    width = np.where(sim < t, s.below, s.above)
    return np.round(0.5 * (1 + np.minimum(1.0, np.abs(sim - t) / width)), 9)


def draw(p: np.ndarray, ids: Sequence[str], size: int, s: Settings, seed: object) -> list[int]:
    """Places of drawn rows, by the scenario's sampler."""
    inside = [i for i in range(len(p)) if p[i] < s.p_limit]
    lots = {i: _lot(seed, ids[i]) for i in inside}
    if s.sampler == "closest":
        return sorted(inside, key=lambda i: (p[i], ids[i]))[:size]
    if s.sampler == "random":
        return sorted(inside, key=lambda i: (lots[i], ids[i]))[:size]
    width, queues = (s.p_limit - 0.5) / s.buckets, {}
    for i in sorted(inside, key=lambda i: (lots[i], ids[i])):
        queues.setdefault(min(int(np.floor(round((p[i] - 0.5) / width, 6))), s.buckets - 1), []).append(i)
    turns = [(turn, b, i) for b, q in queues.items() for turn, i in enumerate(q)]
    return [i for *_, i in sorted(turns)[:size]]


class Run:
    """One run between rounds: reviewed pairs, forest, threshold, metrics."""

    def __init__(self, run_id: str, t_init: float, repetition: int, s: Settings, table: np.ndarray, n_true: int):
        self.run_id, self.t_init, self.t, self.repetition = run_id, t_init, t_init, repetition
        self.pairs = pd.DataFrame()
        self.forest = EvolvingForest(seed=repetition + 1) if s.pretrained is None else pickle.loads(s.pretrained)
        self.round = self.reviews_human = self.updates = 0
        self.metrics: list[dict] = []
        self.note(s, table, n_true)

    def note(self, s: Settings, table: np.ndarray, n_true: int) -> None:
        """A metrics row: histogram at t, corrected by the reviewed pairs' labels."""
        tp, fp = counts_at(table, self.t)
        if len(self.pairs) and s.replace_labels:
            truth, label = self.pairs["truth"].to_numpy(bool), self.labels()[0]
            over = np.round(self.pairs["sim"].to_numpy(float), 9) >= round(self.t, 9)
            tp += int((truth & label).sum()) - int((truth & over).sum())
            fp += int((~truth & label).sum()) - int((~truth & over).sum())
        self.metrics.append(dict(
            run_id=self.run_id, round=self.round, reviews_attr=len(self.pairs), reviews_human=self.reviews_human, tp=tp, fp=fp, fn=n_true - tp,
            f1=f1_of(tp, fp, n_true), threshold=self.t, trees=len(self.forest.trees), updates=self.updates,
        ))
        self.round += 1

    def labels(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Latest label, probability, and whether a human gave it."""
        human = self.pairs["human"].notna().to_numpy()
        label = np.where(human, self.pairs["human"].fillna(0.0).to_numpy() > 0.5, self.pairs["g_attr"].to_numpy(bool))
        return label.astype(bool), np.where(human, 1.0, self.pairs["p_attr"].astype(float)), human

    def relabel(self, s: Settings) -> None:
        """The attribute model's labels of all pairs that no human has seen, in its present state."""
        sim = self.pairs["sim"].to_numpy(float)
        if s.attribute_model == "reuse_top" or not self.forest.trees:
            g, p = np.round(sim, 9) >= round(self.t, 9), ramp(sim, self.t, s)
        else:
            g, p = self.forest.classify(matrix(self.pairs))
        self.pairs["g_attr"], self.pairs["p_attr"] = g, np.round(p, 9)

    def shift(self, s: Settings) -> None:
        self.updates += 1
        if s.update_top:
            label, p, human = self.labels()
            self.t = classify.shift(self.pairs["sim"].to_numpy(float), label, weight(p, human), self.t, self.t_init, s.max_drift, s.max_step, s.measure, STEP)

    def grow(self, s: Settings) -> None:
        """Trees on all reviewed pairs: a human's label, else the top model's."""
        if s.attribute_model != "forest":
            return
        sim, human = self.pairs["sim"].to_numpy(float), self.pairs["human"].notna().to_numpy()
        t = self.t if s.label_source == "current" else self.t_init
        top, p = np.round(sim, 9) >= round(t, 9), ramp(sim, t, s)
        label = np.where(human, self.pairs["human"].fillna(0.0).to_numpy() > 0.5, top)
        self.forest = self.forest.update(matrix(self.pairs), label, weight(p, human))

    def advance(self, new: pd.DataFrame, s: Settings, warm: bool, table: np.ndarray, n_true: int) -> None:
        """One batch of the upper loop, with its lower batches while the warm-up lasts."""
        if len(new):
            new = new.sort_values("pair_id").assign(human=np.nan, g_attr=False, p_attr=0.5, layer="attr", drawn=self.round)
            self.pairs = pd.concat([self.pairs, new], ignore_index=True) if len(self.pairs) else new.reset_index(drop=True)
        if not len(self.pairs):
            self.note(s, table, n_true)
            return
        if not self.forest.trees:
            self.grow(s)
        self.relabel(s)
        self.shift(s)
        if warm and "plain" in s.layers:
            for _ in range(2):
                self.review(s)
                self.grow(s)
                self.relabel(s)
                if s.propagate == "per_lower_batch":
                    self.shift(s)
                    self.note(s, table, n_true)
            if s.propagate == "per_lower_batch":
                return
            self.shift(s)
        self.note(s, table, n_true)

    def review(self, s: Settings) -> None:
        """A lower batch: a human, who is wrong with probability err, labels the forest's uncertain pairs; unused budget is carried on."""
        due = min(s.schedule.budget, s.schedule.lower * (sum(m["round"] > 0 for m in self.metrics) + 1)) if s.propagate == "per_lower_batch" else s.schedule.budget
        size = min(max(0, due - self.reviews_human), 2 * s.schedule.lower) if s.propagate == "per_lower_batch" else min(s.schedule.lower, due - self.reviews_human)
        rows = np.flatnonzero(self.pairs["human"].isna().to_numpy())
        chosen = draw(self.pairs["p_attr"].to_numpy(float)[rows], self.pairs["pair_id"].to_numpy()[rows], size, s, f"{s.seed}.{self.repetition}.{self.updates}")
        for i in rows[chosen]:
            if s.human == "table":
                given = self.pairs.at[i, "given"]
                if pd.isna(given):
                    continue
                self.pairs.at[i, "human"] = float(given)
            else:
                wrong = _uniform(self.pairs.at[i, "pair_id"], f"human{s.seed}.{self.repetition}") < s.err
                self.pairs.at[i, "human"] = float(bool(self.pairs.at[i, "truth"]) != wrong)
            self.pairs.at[i, "layer"] = "plain"
        self.reviews_human += len(chosen)


_STATE = "run_id string, t double, blob binary"


def _row(run: Run) -> pd.DataFrame:
    return pd.DataFrame([(run.run_id, run.t, pickle.dumps(run))], columns=["run_id", "t", "blob"])


def frequency_features(pairs: DataFrame, classes: DataFrame, records: DataFrame) -> DataFrame:
    """(pair_id, fq_<attr>): class of a value that both records share, else 0.  The registry is read once for both sides."""
    sides = F.explode(F.array(*(F.struct(F.lit(s).alias("side"), F.col(f"{s}_id").alias("rec_id")) for s in ("left", "right"))))
    wanted = pairs.select("pair_id", sides.alias("s")).select("pair_id", "s.*")
    values = F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in ATTRIBUTES)))
    each = records.join(sent(wanted), "rec_id").select("pair_id", values.alias("v")).select("pair_id", "v.*").where("value IS NOT NULL")
    shared = each.groupBy("pair_id", "attr", "value").agg(F.count(F.lit(1)).alias("n")).where("n = 2")
    classed = shared.join(classes.select("attr", "value", "freq_class"), ["attr", "value"], "left")
    found = classed.groupBy("pair_id").agg(*(F.max(F.when(F.col("attr") == a, F.col("freq_class"))).alias(f"fq_{a}") for a in ATTRIBUTES))
    return pairs.select("pair_id").join(found, "pair_id", "left").na.fill(0, [f"fq_{a}" for a in ATTRIBUTES])


def _filter_sims(requests: DataFrame, prepared: Prepared) -> DataFrame:
    p = prepared.parameters
    filters = durable(encode.pair_keyed_filters(requests, prepared.records, p))
    return compare.attribute_similarities(filters.where("owner = 'A'"), filters.where("owner = 'B'"), m=p.attribute_m)


def _minhash_sims(requests: DataFrame, prepared: Prepared) -> DataFrame:
    p = prepared.parameters
    signed = durable(encode.pair_keyed_minhash(requests, prepared.records, p))
    return compare.signature_similarities(signed.where("owner = 'A'"), signed.where("owner = 'B'"), p.attributes)


#: Perturbations with a pair's key: requests (owner, rec_id, pair_id, pair_key) and the data to (pair_id, sim_<attr>).
ENCODERS: dict[str, Callable[[DataFrame, Prepared], DataFrame]] = {"filters": _filter_sims, "minhash": _minhash_sims}


def pair_features(pairs: DataFrame, prepared: Prepared, classes: DataFrame, seed: int = 0, rate: float = 1.0, round_: int = 0, key_seed: int | None = None, encoder: str = "filters") -> DataFrame:
    """(pair_id, sim_<attr>, fq_<attr>) for pairs that both owners answer for, each from its own queue."""
    ids = pairs.select(F.explode(F.array("left_id", "right_id")).alias("rec_id")).distinct()
    few = prepared.records.join(sent(ids), "rec_id", "left_semi").repartition(2 * pairs.sparkSession.sparkContext.defaultParallelism, "rec_id")
    prepared = replace(prepared, records=durable(few))  # the registry is read once, and its few records are dealt out
    queue = durable(owner.enqueue(pairs, round_, key_seed))
    pulled = owner.pull(queue, "A").unionByName(owner.pull(queue, "B"))
    replies = owner.Policy(rate, seed).replies(pulled)
    answered = replies.join(owner.complete_pairs(replies), "pair_id") if rate < 1 else replies
    sims = ENCODERS[encoder](answered, prepared)
    usable = pairs if rate >= 1 else pairs.join(owner.complete_pairs(answered), "pair_id", "left_semi")
    return usable.select("pair_id").join(sims, "pair_id", "left").join(frequency_features(usable, classes, prepared.records), "pair_id")


def runs_of(prepared: Prepared, s: Settings, scenario: str = "") -> list[Run]:
    name = f"{scenario}{MARK}" if scenario else ""
    return [
        Run(f"{name}{i:02d}.{r}", round(prepared.t_best + o, 9), r, s, prepared.histogram, prepared.n_true) for i, o in enumerate(s.offsets) for r in range(s.repetitions)
    ]


def scenario_of(run_id: str) -> str:
    return run_id.rpartition(MARK)[0]


def _drawable(candidates: DataFrame, runs: list[tuple[str, float]], reviewed: DataFrame | None, s: Settings, limits: Mapping[str, tuple[float, float]] | None = None) -> DataFrame:
    """(run_id, pair_id, left_id, right_id, sim, truth, p): what each run is uncertain of and has not drawn yet; ``limits`` narrow a run's range."""
    bands = [(run_id, t, *((limits or {}).get(run_id) or classify.uncertain_interval(t, s.p_limit, s.below, s.above))) for run_id, t in runs]
    table = candidates.sparkSession.createDataFrame([(*b, b[0].rpartition(".")[2]) for b in bands], "run_id string, t double, lo double, hi double, repetition string")
    inside = candidates.where((F.col("sim") > min(b[2] for b in bands)) & (F.col("sim") < max(b[3] for b in bands)))
    near = (F.col("sim") > F.col("lo")) & (F.col("sim") < F.col("hi"))
    if "repetition" in candidates.columns:
        near = near & (inside["repetition"] == table["repetition"])
    pairs = inside.join(F.broadcast(table), near)  # a row a run
    pairs = pairs.withColumn("p", classify.ramp(F.col("sim"), F.col("t"), s.below, s.above)).where(F.col("p") < s.p_limit)
    if reviewed is not None:
        pairs = pairs.join(sent(reviewed), ["run_id", "pair_id"], "left_anti")
    return pairs


_ALL = "g"  # over any hexadecimal digit


def _cuts(counts: np.ndarray, wanted: float) -> list[str]:
    """For each bin of similarities a lot (its first hexadecimal digits) under which about ``wanted`` of its pairs have theirs; _ALL where the bin has few."""
    return [_ALL if n <= 4 * wanted else f"{int(wanted / n * 2**32):08x}" for n in counts.tolist()]


def _bin(sim: Column) -> Column:
    return F.least(F.floor(sim / STEP).cast("int"), F.lit(round(1 / STEP)))


def _known(t: float, cuts: Sequence[str], s: Settings) -> list[str]:
    """For each of a run's buckets (one, if the sampler has none) the lot under which all its pairs are known."""
    n = s.buckets if s.sampler == "bucketed" else 1
    width, out = (2 * s.p_limit - 1) / n, []
    for b in range(n):
        sides = ((t - s.below * width * (b + 1), t - s.below * width * b), (t + s.above * width * b, t + s.above * width * (b + 1)))
        out.append(min(cuts[k] for lo, hi in sides for k in range(max(0, int(lo / STEP) - 1), min(len(cuts) - 1, int(hi / STEP) + 1) + 1)))
    return out


def _enough(sizes: Mapping[int, int], known: Sequence[str], size: int) -> bool:
    """Whether a run's draw of ``size`` is settled by its pairs with known lots: ``sizes`` of them in each bucket, which take turns."""
    n = [sizes.get(b, 0) for b in range(len(known))]
    open_ = [x for x, limit in zip(n, known, strict=True) if limit != _ALL]
    if not open_:
        return True
    turns = min(open_)  # each bucket that isn't known whole can take so many turns
    return sum(min(x, turns) for x in n) >= size


def draw_batches(candidates: DataFrame, runs: list[tuple[str, float]], reviewed: DataFrame | None, size: int, s: Settings, round_: int, counts: np.ndarray | None = None, drawn_before: int = 0) -> DataFrame:
    """(run_id, pair_id, left_id, right_id, sim, truth) of each run's next batch.

    Runs (a few dozen rows) are sent to the tasks; the union of their uncertain bands is a range on ``sim``.  ``counts`` (pairs by bins of
    STEP) spare runs the pairs that can't be drawn: a pair's lot is the same for all runs of a repetition, so it is drawn once for
    them, and only low lots go on to the runs.  A run for which these turn out not to settle its draw draws from all its pairs.  The
    closest pairs of a run lie where the counts have the batch and all that it drew before (``drawn_before`` at most).
    """
    if counts is None:
        return _drawn(_drawable(candidates, runs, reviewed, s), size, s, round_)
    if s.sampler == "closest":
        return _drawn(_drawable(candidates, runs, reviewed, s, {run_id: _closest(t, counts, size + drawn_before, s) for run_id, t in runs}), size, s, round_)
    cuts = _cuts(counts, 0.8 * size / s.buckets + 20)
    known = {run_id: _known(t, cuts, s) for run_id, t in runs}
    repetitions = sorted({run_id.rpartition(".")[2] for run_id, _ in runs})
    lots = F.array(*(F.struct(F.lit(r).alias("repetition"), sampling.lot(F.lit(f"{s.seed}.{r}.{round_}"), "pair_id").alias("known_lot")) for r in repetitions))
    low = F.filter(lots, lambda x: x["known_lot"] < F.get(F.lit(cuts), _bin(F.col("sim"))))
    bands = [classify.uncertain_interval(t, s.p_limit, s.below, s.above) for _, t in runs]
    near = candidates.where((F.col("sim") > min(b[0] for b in bands)) & (F.col("sim") < max(b[1] for b in bands)))
    near = near.select("*", F.explode(low).alias("l")).select(*candidates.columns, "l.*")
    limits = candidates.sparkSession.createDataFrame(list(known.items()), "run_id string, known array<string>")
    pairs = _drawable(near, runs, reviewed, s).join(F.broadcast(limits), "run_id")
    bucket = sampling.bucket(F.col("p"), s.p_limit, s.buckets) if s.sampler == "bucketed" else F.lit(0)
    pairs = pairs.withColumn("of", bucket).where(F.col("known_lot") < F.get("known", F.col("of")))
    pairs = durable(pairs.select("run_id", "pair_id", "left_id", "right_id", "sim", "truth", "p", "of"))
    sizes: dict[str, dict[int, int]] = {}
    for row in pairs.groupBy("run_id", "of").count().collect():  # a row a run and bucket
        sizes.setdefault(row["run_id"], {})[row["of"]] = row["count"]
    settled = {run_id for run_id, _ in runs if _enough(sizes.get(run_id, {}), known[run_id], size)}
    drawn = _drawn(pairs.where(F.col("run_id").isin(sorted(settled))), size, s, round_)
    rest = [(run_id, t) for run_id, t in runs if run_id not in settled]
    return drawn.unionByName(_drawn(_drawable(candidates, rest, reviewed, s), size, s, round_)) if rest else drawn


def _closest(t: float, counts: np.ndarray, wanted: int, s: Settings) -> tuple[float, float]:
    """A range around a threshold that has the ``wanted`` pairs of the least p, by whole bins."""
    share = 2 * s.p_limit - 1
    for part in (i / 20 for i in range(1, 20)):
        lo, hi = t - s.below * share * part, t + s.above * share * part
        if counts[int(lo / STEP) + 2 : max(0, int(hi / STEP) - 1)].sum() >= wanted:
            return lo - 1e-6, hi + 1e-6
    return classify.uncertain_interval(t, s.p_limit, s.below, s.above)


def _drawn(pairs: DataFrame, size: int, s: Settings, round_: int) -> DataFrame:
    seed = F.concat_ws(".", F.lit(str(s.seed)), F.substring_index("run_id", ".", -1), F.lit(str(round_)))
    if s.sampler == "bucketed":
        drawn = sampling.bucketed(pairs, size, s.p_limit, s.buckets, seed, by=["run_id"])
    else:
        from pyspark.sql.window import Window

        order = ["p", "pair_id"] if s.sampler == "closest" else [sampling.lot(seed, "pair_id"), "pair_id"]
        drawn = pairs.withColumn("place", F.row_number().over(Window.partitionBy("run_id").orderBy(*order))).where(F.col("place") <= size)
    return drawn.select("run_id", "pair_id", "left_id", "right_id", "sim", "truth")


@dataclass
class Outcome:
    """metrics: a row a run and round; log: a row a run and reviewed pair; features of all encoded pairs."""

    metrics: DataFrame
    log: DataFrame
    features: DataFrame | None


_METRICS = "run_id string, round int, reviews_attr long, reviews_human long, tp long, fp long, fn long, f1 double, threshold double, trees int, updates int"
_LOG = "run_id string, pair_id string, left_id string, right_id string, sim double, truth boolean, drawn int, layer string, g_top boolean, g_attr boolean, p_attr double, g boolean, p double, weight double, " + ", ".join(
    f"sim_{a} double" for a in ATTRIBUTES
)


def _metrics_of(states):
    for rows in states:
        for blob in rows["blob"]:
            yield pd.DataFrame(pickle.loads(blob).metrics)


def _log_of(states):
    names = [x.strip().split()[0] for x in _LOG.split(", ")]
    for rows in states:
        for blob in rows["blob"]:
            run = pickle.loads(blob)
            if len(run.pairs):
                g, p, human = run.labels()
                table = run.pairs.assign(run_id=run.run_id, g=g, p=p, weight=weight(p, human), g_top=np.round(run.pairs["sim"].astype(float), 9) >= round(run.t_init, 9))
                yield table[names]


def _stepper(scenarios: Mapping[str, Settings], warm: bool, table: np.ndarray, n_true: int):
    def step(old: pd.DataFrame, new: pd.DataFrame) -> pd.DataFrame:
        run = pickle.loads(old["blob"].iloc[0])
        run.advance(new.drop(columns="run_id"), scenarios[scenario_of(run.run_id)], warm, table, n_true)
        return _row(run)

    return step


def reach_of(t_best: float, s: Settings) -> tuple[float, float]:
    """Similarities that may be uncertain at any threshold which a run of the scenario can have."""
    lo, hi = (t_best + o + d for o, d in ((min(s.offsets), -s.max_drift), (max(s.offsets), s.max_drift)))
    return classify.uncertain_interval(lo, s.p_limit, s.below, s.above)[0] - STEP, classify.uncertain_interval(hi, s.p_limit, s.below, s.above)[1] + STEP


def _alike(s: Settings) -> tuple:
    """What runs have in common that are drawn together."""
    return s.sampler, s.p_limit, s.buckets, s.below, s.above, s.seed, s.reply_rate if s.ask_more else 1.0


def run_scenarios(prepared: Prepared, scenarios: Mapping[str, Settings], labels: DataFrame | None = None) -> dict[str, Outcome]:
    """All runs of several scenarios that have the same batches of the upper loop: they advance together, round by round.

    ``labels`` (pair_id, g) are those of a human who isn't simulated."""
    spark: SparkSession = prepared.records.sparkSession
    every = list(scenarios.values())
    common = {(s.schedule.small, s.schedule.n_small, s.schedule.big, s.schedule.n_big, s.encoder, s.seed, s.key_seed, "attr" in s.layers) for s in every}
    if len(common) != 1:
        raise ValueError("scenarios that run together have the same batches, encoder and seeds")
    s0, table, n_true = every[0], prepared.histogram, prepared.n_true
    runs = [r for name, s in scenarios.items() for r in runs_of(prepared, s, name)]
    state = durable(spark.createDataFrame(pd.concat([_row(r) for r in runs]), _STATE).repartition(min(len(runs), STATE_PARTS)))
    classes = encode.frequency_classes(prepared.records)
    classes = durable(classes) if "attr" in s0.layers else classes
    rate = max(s.reply_rate for s in every)
    reach = [reach_of(prepared.t_best, s) for s in every]
    reach = min(r[0] for r in reach), max(r[1] for r in reach)
    counts, given, band, before = prepared.histogram.sum(axis=1), None, None, 0
    reviewed = features = None
    batches = [(s0.schedule.small, True)] * s0.schedule.n_small + [(s0.schedule.big, False)] * s0.schedule.n_big
    if "attr" not in s0.layers:
        batches = []
    for round_, (size, warm) in enumerate(batches):
        at = [(r["run_id"], r["t"]) for r in state.select("run_id", "t").collect()]  # a row a run
        wanted = [classify.uncertain_interval(t, s.p_limit, s.below, s.above) for run_id, t in at for s in (scenarios[scenario_of(run_id)],)]
        lo, hi = min(w[0] for w in wanted), max(w[1] for w in wanted)
        if prepared.band is None or lo < prepared.band[0] or hi > prepared.band[1]:
            prepared.within(*prepared.room(lo, hi, reach))
        near = prepared.within(lo, hi)
        if labels is not None and band is not prepared.band:
            given, band = durable(prepared.within(*prepared.band[:2]).select("pair_id").join(labels, "pair_id")), prepared.band
        drawn = None
        for alike in dict.fromkeys(_alike(s) for s in every):
            mine = [(run_id, t) for run_id, t in at if _alike(scenarios[scenario_of(run_id)]) == alike]
            s = scenarios[scenario_of(mine[0][0])]
            asked = sampling.batch_for(size, s.reply_rate) if s.ask_more else size
            found = draw_batches(near, mine, reviewed, asked, s, round_, counts, before)
            drawn = found if drawn is None else drawn.unionByName(found)
        drawn, before = durable(drawn), before + max(sampling.batch_for(size, s.reply_rate) if s.ask_more else size for s in every)
        pairs = drawn.select("pair_id", "left_id", "right_id").distinct()
        if features is not None:
            pairs = pairs.join(sent(features.select("pair_id")), "pair_id", "left_anti")
        found = durable(pair_features(durable(pairs), prepared, classes, s0.seed, rate, round_, s0.key_seed, s0.encoder))
        features = found if features is None else features.unionByName(found)
        news = drawn.join(sent(features), "pair_id")
        rates = {name: s.reply_rate for name, s in scenarios.items() if s.reply_rate < rate}
        if rates:  # owners who answer less give a part of the same answers
            scenario = F.regexp_extract("run_id", f"^(.*){MARK}", 1)
            limit = F.coalesce(F.create_map(*(F.lit(x) for kv in rates.items() for x in kv))[scenario], F.lit(2.0))
            news = news.where(owner.answer_level(s0.seed) < limit)
        if labels is not None:
            news = news.join(given.select("pair_id", F.col("g").cast("double").alias("given")), "pair_id", "left")
        step = _stepper(scenarios, warm, table, n_true)
        state = durable(state.groupBy("run_id").cogroup(news.groupBy("run_id")).applyInPandas(step, _STATE))
        asked = drawn.select("run_id", "pair_id")
        reviewed = asked if reviewed is None else reviewed.unionByName(asked)
    out = {}
    for name in scenarios:
        mine = state.where(F.col("run_id").startswith(f"{name}{MARK}")) if name else state
        bare = F.substring_index("run_id", MARK, -1)
        out[name] = Outcome(mine.mapInPandas(_metrics_of, _METRICS).withColumn("run_id", bare), mine.mapInPandas(_log_of, _LOG).withColumn("run_id", bare), features)
    return out


def run_protocol(prepared: Prepared, s: Settings, labels: DataFrame | None = None) -> Outcome:
    """All runs of a scenario."""
    return run_scenarios(prepared, {"": s}, labels)[""]


def pretrain(prepared: Prepared, size: int = 500, seed: int = 1, key_seed: int | None = None) -> bytes:
    """A forest trained on the uncertain pairs of a data set with known truth, for another data set's attribute layer."""
    t = prepared.t_best
    lo, hi = classify.uncertain_interval(t)
    pairs = classify.threshold(prepared.within(lo - STEP, hi + STEP), t).where(F.col("p") < 0.8)
    drawn = durable(sampling.bucketed(pairs, size, seed=seed).select("pair_id", "left_id", "right_id", "truth"))
    rows = drawn.select("pair_id", "truth").join(pair_features(drawn, prepared, encode.frequency_classes(prepared.records), seed, key_seed=key_seed), "pair_id").toPandas().sort_values("pair_id")  # ``size`` rows
    forest = EvolvingForest(seed=seed)
    for _ in range(10):
        forest = forest.update(matrix(rows, FEATURES), rows["truth"].to_numpy(float), np.ones(len(rows)))
    return pickle.dumps(forest)


def result(candidates: DataFrame, log: DataFrame, t: float) -> DataFrame:
    """The top layer's final result of one run: a human's label, else the attribute model's, else ``sim >= t``."""
    labels = log.select("pair_id", F.col("g").alias("label"), F.col("layer"))
    joined = candidates.join(sent(labels), "pair_id", "left")
    return joined.select("pair_id", "left_id", "right_id", "sim", F.coalesce("label", F.col("sim") >= t).alias("g"), F.coalesce("layer", F.lit("top")).alias("layer"))


def latest(labels: DataFrame) -> DataFrame:
    """Of a log (pair_id, round, layer, g, p, weight) the label that counts: a human's before the forest's before the top's, then the latest."""
    rank = F.when(F.col("layer") == "plain", 3).when(F.col("layer") == "attr", 2).otherwise(1)
    best = labels.groupBy("pair_id").agg(F.max_by(F.struct("layer", "g", "p", "weight", "round"), F.struct(rank, "round")).alias("b"))
    return best.select("pair_id", "b.*")


def changed(before: DataFrame, after: DataFrame) -> DataFrame:
    """Pairs whose outcome (g, p) isn't what was reported before: these only are reported upwards again."""
    old = before.select("pair_id", F.col("g").alias("g0"), F.col("p").alias("p0"))
    return after.join(old, "pair_id", "left").where(~(F.col("g").eqNullSafe(F.col("g0")) & F.col("p").eqNullSafe(F.col("p0")))).drop("g0", "p0")


def with_settings(s: Settings, **changes) -> Settings:
    return replace(s, **changes)
