"""The façade: ask for a model over a range, get it from kept models and as few points as possible."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import SparkSession

from spanfold.functions import bayes, linear
from spanfold.functions.logistic import LogisticState, arrays_of, average_models, make_chunks, project, train_chunks, train_many, train_ranges
from spanfold.operators.batch import range_states
from spanfold.operators.combine import empty, scan_state
from spanfold.plans.costs import LinearCost
from spanfold.plans.planner import Plan, Segment, best_plan, cancel_scans, check_net, explain, scan_plan
from spanfold.plans.ranges import Range
from spanfold.sources.local import MOST_POINTS
from spanfold.sources.points import ModelSpec, PointSource
from spanfold.sources.store import ModelStore


@dataclass
class Answer:
    """A model and how it came about; times in seconds."""

    spec: ModelSpec
    range: Range
    state: object
    plan: Plan
    t_plan: float = 0.0
    t_io: float = 0.0
    t_merge: float = 0.0
    points_read: float = 0.0
    new_models: list = field(default_factory=list)

    @property
    def t_total(self) -> float:
        return self.t_plan + self.t_io + self.t_merge

    def weights(self, ridge: float = 0.0) -> np.ndarray:
        if self.spec.kind == "logit":
            return self.state.w
        return linear.linreg_solve(self.state, ridge, intercept=self.spec.intercept)

    def params(self, **options) -> dict:
        return bayes.gnb_params(self.state, **options) if self.spec.kind == "gnb" else bayes.mnb_params(self.state, **options)


def new_chunks(plan: Plan, spec: ModelSpec, tail: str = "merge") -> list[Range]:
    """Chunks of a logistic plan that no kept model covers."""
    return [c for s in plan.segments if s.kind == "scan" and s.points > 0 for c in make_chunks(s.lo, s.hi, spec.chunk, tail)]


class Engine:
    def __init__(self, spark: SparkSession, store: ModelStore | None = None, cost=LinearCost(), planner: str = "auto"):
        self.spark, self.cost, self.planner = spark, cost, planner
        self.store = store or ModelStore(spark)

    def plan(self, source: PointSource, spec: ModelSpec, lo: int, hi: int, directed: bool | None = None) -> Plan:
        """directed is forced for logistic models, which cannot be subtracted."""
        directed = spec.kind == "logit" if directed is None else directed
        r = Range(lo, hi)
        return best_plan(self.store.relevant(spec, r, directed, source.version), r, self.cost, source.directory, directed, self.planner)

    def fit(self, source: PointSource, spec: ModelSpec, lo: int, hi: int, keep: bool = False, plan: Plan | None = None, tail: str = "merge", anchor: str = "request", weighting: str = "uniform") -> Answer:
        began = time.perf_counter()
        plan = plan or self.plan(source, spec, lo, hi)
        planned = time.perf_counter()
        answer = Answer(spec, Range(lo, hi), None, plan, t_plan=planned - began)
        if spec.kind == "logit":
            self._average(source, answer, keep, tail, anchor, weighting)
        else:
            self._merge(source, answer)
            if keep:
                answer.new_models.append(self.store.put(spec, answer.range, answer.state, source.version))
        return answer

    def _merge(self, source: PointSource, answer: Answer) -> None:
        """Signed merge of fetched models and of one job over what has to be scanned."""
        if not check_net(answer.plan.segments, answer.range):
            raise AssertionError("a plan counts each point of its request once")
        began = time.perf_counter()
        states = self.store.fetch(answer.plan.models, source.version)
        scans = [s for s in cancel_scans(answer.plan.segments, self.cost, source.directory) if s.kind == "scan"]
        scanned = scan_state(source, answer.spec, scans)
        read = time.perf_counter()
        state = empty(answer.spec).combine(scanned)
        for s in answer.plan.segments:
            if s.kind == "model":
                state = state.combine(states[s.model_id], s.sign)
        answer.state, answer.points_read = state, sum(s.points for s in scans)
        answer.t_io, answer.t_merge = read - began, time.perf_counter() - read

    def _average(self, source: PointSource, answer: Answer, keep: bool, tail: str, anchor: str, weighting: str) -> None:
        """Kept chunks inside the request, new chunks for the gaps between them, averaged."""
        spec = answer.spec
        began = time.perf_counter()
        states = list(self.store.fetch(answer.plan.models, source.version).values())
        scans = [s for s in answer.plan.segments if s.kind == "scan" and s.points > 0]
        chunks = [c for s in scans for c in make_chunks(s.lo, s.hi, spec.chunk, tail, anchor)]
        for r, state in self._train(source, spec, scans, chunks):
            states.append(state)
            if keep:
                answer.new_models.append(self.store.put(spec, r, state, source.version))
        read = time.perf_counter()
        answer.state = average_models(states, weighting)
        answer.points_read = sum(s.points for s in scans)
        answer.t_io, answer.t_merge = read - began, time.perf_counter() - read

    def _train(self, source: PointSource, spec: ModelSpec, scans, chunks) -> list[tuple[Range, LogisticState]]:
        """Models of new chunks: on the driver where their points are few and written out, else in
        one job."""
        if not chunks:
            return []
        points = sum(s.hi - s.lo for s in scans)
        source.stats["points"] += points
        ready = source.prepared(spec, project)
        if ready.reader is not None and points <= MOST_POINTS:
            read = [(c, t) for c, t in ((c, ready.reader.read(c.lo, c.hi)) for c in chunks) if t.num_rows]
            parts = [arrays_of(t, spec) for _, t in read]
            return [(c, LogisticState(spec.spec_id, len(y), w)) for (c, _), (_, y), w in zip(read, parts, train_many(parts, spec))]
        source.stats["jobs"] += 1
        rows = train_chunks(ready.scan_segments([Segment(1, "scan", s.lo, s.hi) for s in scans]), spec, chunks, ready=True).collect()
        return [(Range(r.chunk_lo, r.chunk_hi), LogisticState(spec.spec_id, r.n, np.array(r.w))) for r in sorted(rows, key=lambda r: r.chunk_lo)]

    def fit_many(self, source: PointSource, spec: ModelSpec, asks: list[Range], tail: str = "merge", made: dict | None = None) -> list[Answer]:
        """Models for a set of requests: each is planned by itself, and all scans of all plans run as
        one job, over elementary cells or, for logistic models, in one pass through the new chunks
        of all requests; so a point that many plans need is read once. `made`: models of new chunks,
        by range, that a pass for several sets has trained."""
        began = time.perf_counter()
        plans = [self.plan(source, spec, *r) for r in asks]
        planned = time.perf_counter()
        if spec.kind == "logit":
            return self._average_many(source, spec, asks, plans, tail, planned - began, made or {})
        scans = [[s for s in cancel_scans(p.segments, self.cost, source.directory) if s.kind == "scan" and s.hi > s.lo] for p in plans]
        wanted = sorted({Range(s.lo, s.hi) for own in scans for s in own})
        read = dict(zip(wanted, range_states(source, spec, wanted))) if wanted else {}
        models = self.store.fetch(sorted({m for p in plans for m in p.models}), source.version)
        fetched = time.perf_counter()
        out = []
        for r, p, own in zip(asks, plans, scans):
            if not check_net(p.segments, r):
                raise AssertionError("a plan counts each point of its request once")
            state = empty(spec)
            for s in own:
                state = state.combine(read[Range(s.lo, s.hi)], s.sign)
            for s in p.segments:
                if s.kind == "model":
                    state = state.combine(models[s.model_id], s.sign)
            out.append(Answer(spec, r, state, p, points_read=sum(s.points for s in own)))
        merged = time.perf_counter()
        for a in out:  # each carries an even share of the set's time
            a.t_plan, a.t_io, a.t_merge = (planned - began) / len(out), (fetched - planned) / len(out), (merged - fetched) / len(out)
        return out

    def _average_many(self, source: PointSource, spec: ModelSpec, asks, plans, tail: str, t_plan: float, made: dict) -> list[Answer]:
        """As `_average`, with the new chunks of all requests trained together."""
        began = time.perf_counter()
        scans = [[s for s in p.segments if s.kind == "scan" and s.points > 0] for p in plans]
        chunks = [new_chunks(p, spec, tail) for p in plans]
        wanted = sorted({c for own in chunks for c in own} - made.keys())
        made = made | dict(zip(wanted, train_ranges(source, spec, wanted)))
        kept = self.store.fetch(sorted({m for p in plans for m in p.models}), source.version)
        read = time.perf_counter()
        out = []
        for r, p, own, new in zip(asks, plans, scans, chunks):
            state = average_models([*(kept[m] for m in p.models), *(made[c] for c in new)])
            out.append(Answer(spec, r, state, p, points_read=sum(s.points for s in own)))
        merged = time.perf_counter()
        for a in out:  # each carries an even share of the set's time
            a.t_plan, a.t_io, a.t_merge = t_plan / len(out), (read - began) / len(out), (merged - read) / len(out)
        return out

    def extend(self, source: PointSource, answer: Answer, lo: int, hi: int) -> Answer:
        """The model of an answer carried on to [lo, hi). Additive models gain and lose points;
        a logistic model only gains chunks, whose weights join the average."""
        from spanfold.functions.logistic import NotSubtractable
        from spanfold.operators.combine import RangeModel, adjust

        spec, old = answer.spec, answer.range
        if spec.kind != "logit":
            moved = adjust(RangeModel(old, answer.state), lo, hi, source, spec)
            return Answer(spec, moved.range, moved.state, answer.plan)
        if lo > old.lo or hi < old.hi:
            raise NotSubtractable("a logistic model has no points to take away; ask for the smaller range")
        parts = [answer.state]
        for a, b in ((lo, old.lo), (old.hi, hi)):
            if a < b:
                parts.append(self.fit(source, spec, a, b, keep=True).state)
        return Answer(spec, Range(lo, hi), average_models(parts), answer.plan)

    def scratch(self, source: PointSource, spec: ModelSpec, lo: int, hi: int) -> Answer:
        """The baseline: no kept model is used."""
        return self.fit(source, spec, lo, hi, plan=scan_plan(Range(lo, hi), self.cost, source.directory))

    def explain(self, source: PointSource, spec: ModelSpec, lo: int, hi: int) -> dict[str, Plan]:
        return explain(self.store.relevant(spec, Range(lo, hi), source_version=source.version), Range(lo, hi), self.cost, source.directory)
