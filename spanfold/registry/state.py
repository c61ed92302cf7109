"""States, parameters, predictions; incremental change; logistic chunks."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanfold.functions import bayes, linear, logistic
from spanfold.operators import combine as C
from spanfold.operators.baselines import scratch_batch, scratch_gnb, scratch_linreg, scratch_sgd
from spanfold.operators.measures import accuracy
from spanfold.plans.ranges import Range
from spanfold.registry.base import LINES, SCALED, UNITS, events_sql, linreg_sql, query
from spanfold.sources.layout import event_source, lineitem_source
from spanfold.sources.points import CLASS2, CLASS3, DESIGN, GNB_EVENTS, GNB_LINES, LINREG, LOGIT, TARGET, Feature, ModelSpec, PointSource, in_cells, load, spread

SPLIT = "n // 3"  # most ranges run from a third to two thirds of the points


def size_of(source: PointSource) -> int:
    return int(source.directory.running[-1])


def thirds(source: PointSource) -> tuple[int, int]:
    n = size_of(source)
    return n // 3, 2 * n // 3


def tidy_linreg(states: DataFrame, spec: ModelSpec, by=()) -> DataFrame:
    """Packed sums as (by…, i, j, v) rows in real units."""
    cols = spec.columns() + [spec.target]
    have = set(states.columns)
    cells = []
    for i, a in enumerate(cols):
        for j in range(i, len(cols)):
            name = f"c{i}_{j}"
            v = F.col(f"{name}_hi").cast("decimal(38,0)") * F.lit(1 << 32).cast("decimal(12,0)") + F.col(f"{name}_lo") if f"{name}_hi" in have else F.col(name)
            cells.append(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), (v.cast("double") / F.lit(float(a.unit * cols[j].unit))).alias("v")))
    return states.select(*by, F.explode(F.array(*cells)).alias("cell")).select(*by, "cell.*")


def linreg_rows(spark: SparkSession, state) -> DataFrame:
    d, rows = state.width, []
    it = iter(state.cross)
    for i in range(d):
        for j in range(i, d):
            rows.append((i, j, float(next(it)) / (state.units[i] * state.units[j])))
    return spark.createDataFrame(rows, "i int, j int, v double")


def bayes_rows(spark: SparkSession, state, spec: ModelSpec) -> DataFrame:
    rows = [
        (c, f.name, n, float(s[i]) / f.unit, float(q[i]) / (f.unit * f.unit) if q else None)
        for c, (n, s, q) in sorted(state.classes.items()) for i, f in enumerate(spec.features)
    ]
    return spark.createDataFrame(rows, "class string, feature string, n long, s double, q double")


MIDDLE = "pid >= n // 3 and pid < 2 * n // 3"
EVENTS_MIDDLE = "event_id >= n // 3 and event_id < 2 * n // 3"


@query(linreg_sql(MIDDLE))
def linreg_state(spark, sf_dir):
    """Exact state of linear regression over a range: second moments by two-limb integer sums."""
    source = lineitem_source(spark, sf_dir)
    return tidy_linreg(linear.linreg_states(source.scan_range(*thirds(source)), LINREG, points=source.most_points), LINREG)


@query(linreg_sql(MIDDLE))
def linreg_state_decimal(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    return tidy_linreg(linear.linreg_states(source.scan_range(*thirds(source)), LINREG, arithmetic="decimal"), LINREG)


@query(linreg_sql(MIDDLE, "l_returnflag"))
def linreg_state_by_flag(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    return tidy_linreg(linear.linreg_states(source.scan_range(*thirds(source)), LINREG, by=["l_returnflag"], points=source.most_points), LINREG, ["l_returnflag"])


@query(linreg_sql(MIDDLE))
def linreg_state_long(spark, sf_dir):
    """Reference form: every point exploded to all pairs."""
    source = lineitem_source(spark, sf_dir)
    units = F.array(*[F.lit(float(c.unit)) for c in LINREG.columns() + [TARGET]])
    long = linear.linreg_states_long(source.scan_range(*thirds(source)), LINREG)
    return long.select(F.col("i").cast("int"), F.col("j").cast("int"), (F.col("v").cast("double") / (units[F.col("i")] * units[F.col("j")])).alias("v"))


ONE = replace(LINREG, features=(DESIGN[0],))


@query(f"""
with {LINES}, p as (select v1 / 100.0 as x, y / 100.0 as t from full_pts, size where {MIDDLE})
select 'x1' as name, round(regr_slope(t, x), 6) as weight from p union all select 'one', round(regr_intercept(t, x), 6) from p""")
def linreg_weights_2d(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    w = scratch_linreg(source, ONE, *thirds(source))
    return spark.createDataFrame([(c.name, round(float(v), 6)) for c, v in zip(ONE.columns(), w)], "name string, weight double")


@query(f"""
with {LINES},
m as (select sum(v1 * v1)::double / 1e4 as aa, sum(v1 * v3)::double / 1e4 as ab, sum(v3 * v3)::double / 1e4 as bb, sum(v1 * y)::double / 1e4 as ay, sum(v3 * y)::double / 1e4 as cy
  from full_pts, size where {MIDDLE}),
r as (select *, aa + 10.0 as ra, bb + 10.0 as rb from m)
select 'x1' as name, round((ay * rb - ab * cy) / (ra * rb - ab * ab), 6) as weight from r
union all select 'x3', round((ra * cy - ab * ay) / (ra * rb - ab * ab), 6) from r""")
def linreg_ridge_2d(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    two = replace(LINREG, features=(DESIGN[0], DESIGN[2]), intercept=False)
    w = scratch_linreg(source, two, *thirds(source), ridge=10.0)
    return spark.createDataFrame([(c.name, round(float(v), 6)) for c, v in zip(two.columns(), w)], "name string, weight double")


@query(f"""
with {LINES}, p as (select v1 / 100.0 as x, y / 100.0 as t from full_pts, size where {MIDDLE}),
s as (select count(*) as n, regr_r2(t, x) as r2, regr_syy(t, x) as sst from p)
select n, round(r2, 6) as r2, round((1 - r2) * sst, 2) as sse, round(sst, 2) as sst, round(r2 * sst / ((1 - r2) * sst / (n - 2)), 2) as f, round(n * ln((1 - r2) * sst / n) + 4, 2) as aic from s""")
def linreg_fit_quality(spark, sf_dir):
    """R², F and AIC from the kept state alone."""
    source = lineitem_source(spark, sf_dir)
    state = C.build(source, ONE, *thirds(source)).state
    a = linear.linreg_anova(state, linear.linreg_solve(state), intercept=True)
    return spark.createDataFrame([(a["n"], round(a["r2"], 6), round(a["sse"], 2), round(a["sst"], 2), round(a["f"], 2), round(a["aic"], 2))], "n long, r2 double, sse double, sst double, f double, aic double")


@query(f"""
with recursive {LINES}, p as (select [1, v1, v2, v3, v4, v5, v6, v7, v8, v9, v10, y]::hugeint[] as x from full_pts, size where {MIDDLE}),
cell as (select i, j, cast(sum(x[i] * x[j]) as double) / ({UNITS}[i] * {UNITS}[j]) + case when i = j then 1.0 else 0.0 end as v
  from p, (select unnest(range(1, 12)) as i) a, (select unnest(range(1, 13)) as j) b group by i, j),
rws as (select i, list(v order by j) as r from cell group by i),
el(k, m) as (select 0, list(r order by i) from rws union all
  select k + 1, list_transform(m, lambda r, i: case when i = k + 1 then list_transform(r, lambda x: x / m[k + 1][k + 1]) else list_transform(r, lambda x, j: x - r[k + 1] * (m[k + 1][j] / m[k + 1][k + 1])) end) from el where k < 11)
select case when i = 1 then 'one' else 'x' || (i - 1) end as name, round(m[i][12], 5) as weight from el, (select unnest(range(1, 12)) as i) where k = 11""")
def linreg_weights_10d(spark, sf_dir):
    """All ten features and a constant, with a penalty of one."""
    source = lineitem_source(spark, sf_dir)
    w = scratch_linreg(source, LINREG, *thirds(source), ridge=1.0)
    return spark.createDataFrame([(c.name, round(float(v), 5)) for c, v in zip(LINREG.columns(), w)], "name string, weight double")


@query(f"""
with {LINES}, m as (select regr_slope(y / 100.0, v1 / 100.0) as b, regr_intercept(y / 100.0, v1 / 100.0) as a from full_pts, size where {MIDDLE})
select count(*) as n, round(avg((y / 100.0 - a - b * v1 / 100.0) * (y / 100.0 - a - b * v1 / 100.0)), 4) as mse from full_pts, m""")
def linreg_predict_mse(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    w = scratch_linreg(source, ONE, *thirds(source))
    e = F.col("prediction") - TARGET.real()
    return linear.linreg_predict(source.df, ONE, w).agg(F.count("*").alias("n"), F.round(F.avg(e * e), 4).alias("mse"))


@query("""
with e as (select list_transform(embedding, lambda x: cast(x as double)) as x from embeddings), idx as (select i, j from (select unnest(range(64)) as i), (select unnest(range(64)) as j) where i <= j)
select cast(i as int) as i, cast(j as int) as j, round(sum(x[i + 1] * x[j + 1]), 6) + 0.0 as v from e, idx group by i, j""")
def embedding_gram(spark, sf_dir):
    """64 × 64 second moments by Arrow batches: 2,080 cells."""
    g = linear.linreg_state_arrow(load(spark, sf_dir, "embeddings"), "embedding")
    return g.select("i", "j", (F.round("v", 6) + F.lit(0.0)).alias("v"))


# naive Bayes


@query(events_sql(EVENTS_MIDDLE))
def gnb_state(spark, sf_dir):
    source = event_source(spark, sf_dir)
    return bayes_rows(spark, C.build(source, GNB_EVENTS, *thirds(source)).state, GNB_EVENTS)


@query(f"""
with s as ({events_sql(EVENTS_MIDDLE)}), t as (select sum(n) as total from s where feature = 'value')
select class, feature, round(n / total, 6) as prior, round(s / n, 6) as mean, round(q / n - (s / n) * (s / n), 4) as variance from s, t""")
def gnb_params(spark, sf_dir):
    source = event_source(spark, sf_dir)
    p = scratch_gnb(source, GNB_EVENTS, *thirds(source))
    rows = [(c, f.name, round(prior, 6), round(m[i], 6), round(v[i], 4)) for c, (prior, m, v) in p.items() for i, f in enumerate(GNB_EVENTS.features)]
    return spark.createDataFrame(rows, "class string, feature string, prior double, mean double, variance double")


_GNB_LINE_PARAMS = f"""
{LINES},
half as (select c3, unnest([v1 / 100.0, v3 / 100.0, v4 / 100.0]::double[]) as x, unnest([0, 1, 2]) as j from full_pts, size where pid < n // 2),
par as (select c3, j, count(*) as n, avg(x) as m, var_pop(x) as v from half group by c3, j),
pri as (select c3, ln(n * 1.0 / sum(n) over ()) as lp from par where j = 0),
rest as (select pid, c3 as truth, unnest([v1 / 100.0, v3 / 100.0, v4 / 100.0]::double[]) as x, unnest([0, 1, 2]) as j from full_pts, size where pid >= n // 2),
sco as (select pid, truth, par.c3, max(lp) - sum(0.5 * ln(2 * pi() * v) + (x - m) * (x - m) / (2 * v)) as s from rest join par using (j) join pri on pri.c3 = par.c3 group by pid, truth, par.c3),
top as (select pid, truth, c3, row_number() over (partition by pid order by s desc, c3) as rk from sco)"""


@query(f"with {_GNB_LINE_PARAMS} select count(*) as n, count_if(truth = c3) as correct from top where rk = 1")
def gnb_predict_accuracy(spark, sf_dir):
    """Train on the first half of the points, classify the second."""
    source = lineitem_source(spark, sf_dir)
    n = size_of(source)
    spec = replace(GNB_LINES, features=(DESIGN[0], DESIGN[2], DESIGN[3]))
    scores = bayes.gnb_scores(spec, scratch_gnb(source, spec, 0, n // 2))
    return accuracy(bayes.predict(bayes.featured(source.scan_range(n // 2, n), spec), scores), CLASS3).select("n", "correct")


@query("select event_type as class, count(*) as n, round(count(*) * 1.0 / sum(count(*)) over (), 6) as prior from events group by event_type")
def class_prior(spark, sf_dir):
    source = event_source(spark, sf_dir)
    state = C.build(source, GNB_EVENTS, 0, size_of(source)).state
    return spark.createDataFrame([(c, state.classes[c][0], round(p, 6)) for c, p in bayes.class_prior(state).items()], "class string, n long, prior double")


# The letters counted.
LETTERS = "abcdefghijklmnopqrstuvwxyzéèêçàùôîâûäöüßñáíóú"
LETTER_SPEC = ModelSpec("mnb", "documents", "doc_id", tuple(Feature(c, f"low_n - length(replace(low, '{c}', ''))") for c in LETTERS), "lang", classes=("de", "en", "es", "fr"))
LETTERS_SQL = "counts as (select doc_id, lang, l, length(lower(text)) - length(replace(lower(text), l, '')) as c from documents, (select unnest(string_split('" + ",".join(LETTERS) + "', ',')) as l))"


def letters_source(spark, sf_dir):
    # lower-cased and measured once a text, not once a letter
    rows = spread(load(spark, sf_dir, "documents").select("doc_id", "text", "lang")).withColumn("low", F.lower("text")).withColumn("low_n", F.length("low"))
    return PointSource(rows, "doc_id", sf_dir)


@query(f"with {LETTERS_SQL} select lang as class, l as feature, count(*) as n, cast(sum(c) as double) as s from counts group by lang, l")
def mnb_state_letters(spark, sf_dir):
    return bayes_rows(spark, bayes.bayes_state(letters_source(spark, sf_dir).df, LETTER_SPEC), LETTER_SPEC).drop("q")


@query(f"""
with {LETTERS_SQL}, m as (select lang, l, sum(c) as c, count(*) as n from counts group by lang, l)
select lang as class, l as feature, round(n * 1.0 / (select count(*) from documents), 6) as prior, round((c + 1) * 1.0 / (sum(c) over (partition by lang) + 45), 9) as theta from m""")
def mnb_params_letters(spark, sf_dir):
    p = bayes.mnb_params(bayes.bayes_state(letters_source(spark, sf_dir).df, LETTER_SPEC))
    return spark.createDataFrame([(c, f.name, round(prior, 6), round(t, 9)) for c, (prior, th) in p.items() for f, t in zip(LETTER_SPEC.features, th)], "class string, feature string, prior double, theta double")


@query(f"""
with {LETTERS_SQL}, size as (select count(*) as n from documents),
m as (select lang, l, sum(c) as c, count(*) as n from counts where doc_id < (select n // 2 from size) group by lang, l),
th as (select lang, l, ln((c + 1) * 1.0 / (sum(c) over (partition by lang) + 45)) as lt, ln(n * 1.0 / (select n // 2 from size)) as lp from m),
sco as (select doc_id, counts.lang as truth, th.lang as c, max(lp) + sum(counts.c * lt) as s from counts join th using (l) where doc_id >= (select n // 2 from size) group by doc_id, counts.lang, th.lang),
top as (select *, row_number() over (partition by doc_id order by s desc, c) as rk from sco)
select count(*) as n, count_if(truth = c) as correct from top where rk = 1""")
def mnb_predict_lang(spark, sf_dir):
    """Train on the first half of the texts, tell the language of the rest, by letters."""
    source = letters_source(spark, sf_dir)
    n = source.df.count()
    letters = F.split("low", "")
    params = bayes.mnb_params(bayes.mnb_state_sparse(source.scan_range(0, n // 2), LETTER_SPEC, letters))
    return accuracy(bayes.mnb_predict_sparse(source.scan_range(n // 2, n), LETTER_SPEC, letters, params, "doc_id"), "class").select("n", "correct")


@query(f"""
with {LETTERS_SQL}, size as (select count(*) as n from documents),
m as (select lang, l, sum(c) as c, count(*) as n from counts where doc_id < (select n // 2 from size) group by lang, l),
th as (select lang, l, ln((c + 1) * 1.0 / (sum(c) over (partition by lang) + 45)) as lt, ln(n * 1.0 / (select n // 2 from size)) as lp from m),
sco as (select doc_id, th.lang as c, max(lp) + sum(counts.c * lt) as s from counts join th using (l) where doc_id >= (select n // 2 from size) group by doc_id, th.lang),
top as (select *, row_number() over (partition by doc_id order by s desc, c) as rk from sco)
select c as prediction, count(*) as n from top where rk = 1 group by c""")
def mnb_predict_dense(spark, sf_dir):
    """The same by a score a class inside the scan, from counts as columns: nothing is shuffled, but
    every feature is counted by a pass over the text; for few features."""
    source = letters_source(spark, sf_dir)
    n = source.df.count()
    params = bayes.mnb_params(bayes.mnb_state_sparse(source.scan_range(0, n // 2), LETTER_SPEC, F.split("low", "")))
    scored = bayes.predict(bayes.featured(source.scan_range(n // 2, n), LETTER_SPEC), bayes.mnb_scores(LETTER_SPEC, params))
    return scored.groupBy("prediction").agg(F.count("*").alias("n"))


@query(f"with {LETTERS_SQL} select lang as class, l as feature, count(*) as n, cast(sum(c) as double) as s from counts group by lang, l")
def mnb_state_sparse(spark, sf_dir):
    """The letters' state from one pass over exploded letters."""
    return bayes_rows(spark, bayes.mnb_state_sparse(letters_source(spark, sf_dir).df, LETTER_SPEC, F.split("low", "")), LETTER_SPEC).drop("q")


# Classes of characters counted, as patterns.
SYMBOLS = {"letters": "[A-Za-z]", "digits": "[0-9]", "blanks": " ", "marks": "[%*#&$!@]"}
SYMBOL_SPEC = ModelSpec("mnb", "labels", "doc_id", tuple(Feature(k, f"regexp_count(text, '{p}')") for k, p in SYMBOLS.items()), "cast(quality as string)", classes=("0", "1"))


@query("select cast(quality as varchar) as class, k as feature, count(*) as n, cast(sum(length(text) - length(regexp_replace(text, p, '', 'g'))) as double) as s from documents join labels using (doc_id), "
       "(select unnest(['letters', 'digits', 'blanks', 'marks']) as k, unnest(['[A-Za-z]', '[0-9]', ' ', '[%*#&$!@]']) as p) group by quality, k")  # fmt: skip
def mnb_symbols_quality(spark, sf_dir):
    rows = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")
    return bayes_rows(spark, bayes.bayes_state(rows, SYMBOL_SPEC), SYMBOL_SPEC).drop("q")


@query("select role as class, count(*) as n, cast(sum(len(regexp_extract_all(text, '[A-Za-z]+'))) as double) as words from conversations group by role")
def mnb_words_role(spark, sf_dir):
    spec = ModelSpec("mnb", "conversations", "conv_id", (Feature("words", "regexp_count(text, '[A-Za-z]+')"),), "role")
    return bayes_rows(spark, bayes.bayes_state(load(spark, sf_dir, "conversations"), spec), spec).select("class", "n", F.col("s").alias("words"))


@query("""select regexp_extract(html, '<html lang="([a-z]+)"', 1) as class, count(*) as n, cast(sum(len(regexp_extract_all(html, '<p[ >]'))) as double) as paragraphs,
cast(sum(len(regexp_extract_all(html, '<a[ >]'))) as double) as anchors from pages group by 1""")
def mnb_tags_language(spark, sf_dir):
    spec = ModelSpec("mnb", "pages", "page_id", (Feature("p", "regexp_count(html, '<p[ >]')"), Feature("a", "regexp_count(html, '<a[ >]')")), "regexp_extract(html, '<html lang=\"([a-z]+)\"', 1)")
    return bayes.bayes_states(load(spark, sf_dir, "pages"), spec).select("class", "n", F.col("s0").cast("double").alias("paragraphs"), F.col("s1").cast("double").alias("anchors"))


@query(f"""
with {_GNB_LINE_PARAMS}, mx as (select pid, max(s) as b from sco group by pid),
po as (select pid, c3, exp(s - b) / sum(exp(s - b)) over (partition by pid) as p from sco join mx using (pid))
select c3 as class, round(avg(p), 6) as mean_posterior from po group by c3""")
def nb_posterior(spark, sf_dir):
    """Mean posterior of each class over the second half of the points."""
    source = lineitem_source(spark, sf_dir)
    n = size_of(source)
    spec = replace(GNB_LINES, features=(DESIGN[0], DESIGN[2], DESIGN[3]))
    scores = bayes.gnb_scores(spec, scratch_gnb(source, spec, 0, n // 2))
    rows = bayes.posteriors(bayes.featured(source.scan_range(n // 2, n), spec), scores).select(F.explode("posterior").alias("class", "p"))
    return rows.groupBy("class").agg(F.round(F.avg("p"), 6).alias("mean_posterior"))


# incremental change: each result equals the state of the target range built from scratch


def _parts(source):
    n = size_of(source)
    return n // 4, n // 2, 3 * n // 4, n


@query(linreg_sql("pid >= n // 4 and pid < 3 * n // 4"))
def linreg_add_points(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    a, b, c, _ = _parts(source)
    state = C.build(source, LINREG, a, b).state
    return linreg_rows(spark, state.combine(linear.linreg_state(source.scan_range(b, c), LINREG)))


@query(linreg_sql("pid >= n // 4 and pid < n // 2"))
def linreg_remove_points(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    a, b, c, _ = _parts(source)
    state = C.build(source, LINREG, a, c).state
    return linreg_rows(spark, state.combine(linear.linreg_state(source.scan_range(b, c), LINREG), -1))


@query(linreg_sql("pid >= n // 4 and pid <= n // 2"))
def linreg_add_one_point(spark, sf_dir):
    """One more point, given by its values."""
    source = lineitem_source(spark, sf_dir)
    a, b, _, _ = _parts(source)
    state = C.build(source, LINREG, a, b).state
    cols = LINREG.columns() + [LINREG.target]
    row = source.scan_range(b, b + 1).select(*[(c.integer() / F.lit(c.unit)).alias(f"v{i}") for i, c in enumerate(cols)]).first()
    return linreg_rows(spark, linear.linreg_add(state, LINREG, list(row)[1:-1], row[-1]))


@query(linreg_sql("pid >= n // 4 and pid < n // 2 - 1"))
def linreg_remove_one_point(spark, sf_dir):
    """The last point taken out again, given by its values."""
    source = lineitem_source(spark, sf_dir)
    a, b, _, _ = _parts(source)
    state = C.build(source, LINREG, a, b).state
    cols = LINREG.columns() + [LINREG.target]
    row = source.scan_range(b - 1, b).select(*[(c.integer() / F.lit(c.unit)).alias(f"v{i}") for i, c in enumerate(cols)]).first()
    return linreg_rows(spark, linear.linreg_remove(state, LINREG, list(row)[1:-1], row[-1]))


@query(events_sql("event_id >= n // 4 and event_id <= n // 2"))
def gnb_add_one_point(spark, sf_dir):
    source = event_source(spark, sf_dir)
    a, b, _, _ = _parts(source)
    state = C.build(source, GNB_EVENTS, a, b).state
    row = source.scan_range(b, b + 1).select(F.expr(GNB_EVENTS.label).alias("class"), *[f.real().alias(f.name) for f in GNB_EVENTS.features]).first()
    return bayes_rows(spark, state.combine(bayes.point_state(GNB_EVENTS, list(row)[1:], row[0])), GNB_EVENTS)


@query(events_sql("event_id >= n // 4 and event_id < 3 * n // 4"))
def gnb_add_points(spark, sf_dir):
    source = event_source(spark, sf_dir)
    a, b, c, _ = _parts(source)
    state = C.build(source, GNB_EVENTS, a, b).state
    return bayes_rows(spark, state.combine(bayes.bayes_state(source.scan_range(b, c), GNB_EVENTS)), GNB_EVENTS)


@query(events_sql("event_id >= n // 2 and event_id < 3 * n // 4"))
def gnb_remove_points(spark, sf_dir):
    source = event_source(spark, sf_dir)
    a, b, c, _ = _parts(source)
    state = C.build(source, GNB_EVENTS, a, c).state
    return bayes_rows(spark, state.combine(bayes.bayes_state(source.scan_range(a, b), GNB_EVENTS), -1), GNB_EVENTS)


@query(f"with {LETTERS_SQL} select lang as class, l as feature, count(*) as n, cast(sum(c) as double) as s from counts where doc_id < 3 * (select count(*) from documents) // 4 group by lang, l")
def mnb_add_points(spark, sf_dir):
    source = letters_source(spark, sf_dir)
    n = source.df.count()
    first = bayes.bayes_state(source.scan_range(0, n // 2), LETTER_SPEC)
    return bayes_rows(spark, first.combine(bayes.bayes_state(source.scan_range(n // 2, 3 * n // 4), LETTER_SPEC)), LETTER_SPEC).drop("q")


@query(f"with {LETTERS_SQL} select lang as class, l as feature, count(*) as n, cast(sum(c) as double) as s from counts where doc_id < (select count(*) from documents) // 2 group by lang, l")
def mnb_remove_points(spark, sf_dir):
    source = letters_source(spark, sf_dir)
    n = source.df.count()
    every = bayes.bayes_state(source.df, LETTER_SPEC)
    return bayes_rows(spark, every.combine(bayes.bayes_state(source.scan_range(n // 2, n), LETTER_SPEC), -1), LETTER_SPEC).drop("q")


@query(events_sql("event_id >= n // 4"))
def combine_disjoint(spark, sf_dir):
    source = event_source(spark, sf_dir)
    a, b, _, n = _parts(source)
    return bayes_rows(spark, C.combine(C.build(source, GNB_EVENTS, a, b), C.build(source, GNB_EVENTS, b, n)).state, GNB_EVENTS)


def _overlapping(spark, sf_dir, via):
    source = lineitem_source(spark, sf_dir)
    from spanfold.operators.batch import range_states

    a, b, c, n = _parts(source)
    spans = [Range(a, c), Range(b, n)]
    one, two = (C.RangeModel(r, s) for r, s in zip(spans, range_states(source, LINREG, spans)))
    return linreg_rows(spark, C.combine(one, two, source, LINREG, via).state)


@query(linreg_sql("pid >= n // 4"))
def combine_overlap_minus(spark, sf_dir):
    return _overlapping(spark, sf_dir, "minus_intersection")


@query(linreg_sql("pid >= n // 4"))
def combine_overlap_first_rest(spark, sf_dir):
    return _overlapping(spark, sf_dir, "first_plus_rest")


@query(linreg_sql("pid >= n // 4"))
def combine_overlap_second_rest(spark, sf_dir):
    return _overlapping(spark, sf_dir, "second_plus_rest")


@query(linreg_sql("pid >= n // 4"))
def combine_overlap_auto(spark, sf_dir):
    return _overlapping(spark, sf_dir, "auto")


def _bayes_overlap(spark, sf_dir, via):
    source = event_source(spark, sf_dir)
    a, b, c, n = _parts(source)
    return bayes_rows(spark, C.combine(C.build(source, GNB_EVENTS, a, c), C.build(source, GNB_EVENTS, b, n), source, GNB_EVENTS, via).state, GNB_EVENTS)


@query(events_sql("event_id >= n // 4"))
def gnb_overlap_minus(spark, sf_dir):
    return _bayes_overlap(spark, sf_dir, "minus_intersection")


@query(events_sql("event_id >= n // 4"))
def gnb_overlap_first_rest(spark, sf_dir):
    return _bayes_overlap(spark, sf_dir, "first_plus_rest")


@query(events_sql("event_id >= n // 4"))
def gnb_overlap_second_rest(spark, sf_dir):
    return _bayes_overlap(spark, sf_dir, "second_plus_rest")


def _letters_overlap(spark, sf_dir, via):
    source = letters_source(spark, sf_dir)
    n = source.df.count()
    one, two = (C.build(source, LETTER_SPEC, lo, hi) for lo, hi in ((n // 4, 3 * n // 4), (n // 2, n)))
    return bayes_rows(spark, C.combine(one, two, source, LETTER_SPEC, via).state, LETTER_SPEC).drop("q")


_LATER_LETTERS = f"with {LETTERS_SQL} select lang as class, l as feature, count(*) as n, cast(sum(c) as double) as s from counts where doc_id >= (select count(*) from documents) // 4 group by lang, l"


@query(_LATER_LETTERS)
def mnb_overlap_minus(spark, sf_dir):
    return _letters_overlap(spark, sf_dir, "minus_intersection")


@query(_LATER_LETTERS)
def mnb_overlap_first_rest(spark, sf_dir):
    return _letters_overlap(spark, sf_dir, "first_plus_rest")


@query(_LATER_LETTERS)
def mnb_overlap_second_rest(spark, sf_dir):
    return _letters_overlap(spark, sf_dir, "second_plus_rest")


@query(linreg_sql("pid >= n // 4 and pid < n * 9 // 10"))
def merge_signed_states(spark, sf_dir):
    """Stored states added and subtracted inside Spark: [0, n) − [0, n/4) − [9n/10, n)."""
    from spanfold.operators.batch import range_states

    source = lineitem_source(spark, sf_dir)
    n = size_of(source)
    spans = [Range(0, n), Range(0, n // 4), Range(n * 9 // 10, n)]
    states = range_states(source, LINREG, spans)
    rows = [(LINREG.spec_id, sign, [str(v) for v in s.cross]) for s, sign in zip(states, (1, -1, -1))]
    kept = spark.createDataFrame(rows, "spec_id string, sign int, text array<string>").select("spec_id", "sign", F.transform("text", lambda v: v.cast("decimal(35,0)")).alias("values"))
    units = [c.unit for c in LINREG.columns() + [TARGET]]
    at = [(i, j, float(units[i] * units[j])) for i in range(len(units)) for j in range(i, len(units))]
    cells = spark.createDataFrame([(k, i, j, u) for k, (i, j, u) in enumerate(at)], "k int, i int, j int, u double")  # 78 rows
    return C.merge_signed(kept).withColumnRenamed("i", "k").join(F.broadcast(cells), "k").select("i", "j", (F.col("v").cast("double") / F.col("u")).alias("v"))


@query(linreg_sql("pid >= n // 2"))
def subtract_contained(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    a, b, _, n = _parts(source)
    return linreg_rows(spark, C.subtract(C.build(source, LINREG, a, n), C.build(source, LINREG, a, b)).state)


# The month of the events, its first half and its second week.
MONTH, HALF, WEEK = ("2024-01-01", "2024-01-31"), ("2024-01-01", "2024-01-16"), ("2024-01-08", "2024-01-15")


def _moved(spark, sf_dir, old, new):
    from spanfold.sources.points import time_ranges_keys

    source = event_source(spark, sf_dir)
    before, after = [(r.lo, r.hi) for r in time_ranges_keys(source.df, "event_id", "ts", [old, new]).orderBy("seq").collect()]  # two rows
    return bayes_rows(spark, C.adjust(C.build(source, GNB_EVENTS, *before), *after, source, GNB_EVENTS).state, GNB_EVENTS)


@query(events_sql("ts >= timestamp '2024-01-01' and ts < timestamp '2024-01-31'"))
def month_first_half_extend(spark, sf_dir):
    return _moved(spark, sf_dir, HALF, MONTH)


@query(events_sql("ts >= timestamp '2024-01-08' and ts < timestamp '2024-01-15'"))
def month_drill_week(spark, sf_dir):
    return _moved(spark, sf_dir, MONTH, WEEK)


@query(events_sql("ts >= timestamp '2024-01-01' and ts < timestamp '2024-01-16'"))
def month_shrink(spark, sf_dir):
    return _moved(spark, sf_dir, MONTH, HALF)


# logistic regression by chunks

ONE_STEP = replace(LOGIT, trainer="batch", steps=1, step_size=0.5, l2=0.01)
FIXED_W = [0.1 * (i - 5) for i in range(11)]
CHUNKS = 6


def _chunk_cuts(n: int) -> list[Range]:
    size = n // CHUNKS
    return logistic.make_chunks(0, size * CHUNKS, size)


@query(f"""
with {LINES}, {SCALED}, p as (select [{', '.join(map(str, FIXED_W))}]::double[] as w), z as (select c2, list_dot_product(x, w) as z from sc, p)
select round(avg(greatest(z, 0) - z * c2 + ln(1 + exp(-abs(z)))) + 0.01 * {sum(x * x for x in FIXED_W)}, 6) as loss from z""")
def logit_loss_fixed_w(spark, sf_dir):
    return logistic.logit_loss(lineitem_source(spark, sf_dir).df, LOGIT, FIXED_W, 0.01).select(F.round("loss", 6).alias("loss"))


@query(f"""
with {LINES}, {SCALED} select cast(j as int) as j, round(avg((0.5 - c2) * x[j + 1]), 10) as g from sc, (select unnest(range(11)) as j) group by j""")
def logit_gradient_zero(spark, sf_dir):
    g = logistic.logit_gradient(lineitem_source(spark, sf_dir).df, LOGIT, [0.0] * 11)
    return g.select(F.posexplode(F.array(*[F.round(f"g{j}", 10) for j in range(11)])).alias("j", "g"))


def _step_sql(steps: int) -> str:
    """Unrolled full-batch steps for each chunk, from zero."""
    out = f"with {LINES}, {SCALED}, ch as (select *, pid // (n // {CHUNKS}) as c from sc, size where pid < (n // {CHUNKS}) * {CHUNKS}), w0 as (select distinct c, list_transform(range(11), lambda x: 0.0)::double[] as w from ch)"
    for t in range(steps):
        out += f""",
g{t} as (select ch.c, j, avg((1 / (1 + exp(-list_dot_product(x, w))) - c2) * x[j + 1]) + 0.02 * max(w[j + 1]) as g, max(w[j + 1]) as v
  from ch join w{t} on ch.c = w{t}.c, (select unnest(range(11)) as j) group by ch.c, j),
w{t + 1} as (select c, list(v - 0.5 * g order by j) as w from g{t} group by c)"""
    return out


def _trained(spark, sf_dir, steps):
    source = lineitem_source(spark, sf_dir)
    return logistic.train_chunks(source.df, replace(ONE_STEP, steps=steps), _chunk_cuts(size_of(source)))


def _chunk_rows(trained):
    return trained.select((F.floor(F.col("chunk_lo") / (F.col("chunk_hi") - F.col("chunk_lo")))).cast("long").alias("c"), F.posexplode("w").alias("j", "w")).select("c", "j", F.round("w", 10).alias("w"))


@query(_step_sql(1) + " select c, cast(j as int) as j, round(w[j + 1], 10) as w from w1, (select unnest(range(11)) as j)")
def logit_chunk_one_step(spark, sf_dir):
    return _chunk_rows(_trained(spark, sf_dir, 1))


@query(_step_sql(3) + " select c, cast(j as int) as j, round(w[j + 1], 10) as w from w3, (select unnest(range(11)) as j)")
def logit_chunk_three_steps(spark, sf_dir):
    return _chunk_rows(_trained(spark, sf_dir, 3))


@query(_step_sql(3) + " select cast(j as int) as i, round(avg(w[j + 1]), 6) as w from w3, (select unnest(range(11)) as j) group by j")
def logit_average_uniform(spark, sf_dir):
    return logistic.average_frame(_trained(spark, sf_dir, 3)).select("i", F.round("w", 6).alias("w"))


@query(_step_sql(1).replace("pid < (n // 6) * 6", "true").replace("pid // (n // 6)", "case when pid < n // 6 then 0 else 1 end")
       + " select cast(j as int) as i, round(sum(w[j + 1] * case when c = 0 then n // 6 else n - n // 6 end) / max(n), 6) as w from w1, size, (select unnest(range(11)) as j) group by j")
def logit_average_by_points(spark, sf_dir):
    """Two chunks of different sizes, weighed by their points."""
    source = lineitem_source(spark, sf_dir)
    n = size_of(source)
    trained = logistic.train_chunks(source.df, ONE_STEP, [Range(0, n // 6), Range(n // 6, n)])
    return logistic.average_frame(trained, "by_points").select("i", F.round("w", 6).alias("w"))


@query(_step_sql(3) + """, a as (select list(m order by j) as w from (select j, avg(w[j + 1]) as m from w3, (select unnest(range(11)) as j) group by j))
select count(*) as n, count_if((list_dot_product(x, w) >= 0) = (c2 = 1)) as correct from sc, a""")
def logit_predict_accuracy(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    rows = _trained(spark, sf_dir, 3).collect()
    w = logistic.average_models([logistic.LogisticState("x", r.n, np.array(r.w)) for r in rows]).w
    return accuracy(logistic.logit_predict(source.df, LOGIT, w), CLASS2).select("n", "correct")


@query(_step_sql(3) + " select cast(j as int) as i, round(avg(w[j + 1]), 6) as w from w3, (select unnest(range(11)) as j) where c >= 1 and c < 5 group by j")
def logit_reuse_answer(spark, sf_dir):
    """A request over four chunks, two of them kept: the answer is that of building all four."""
    from spanfold.engine import Engine

    source = lineitem_source(spark, sf_dir)
    size = size_of(source) // CHUNKS
    spec = replace(ONE_STEP, steps=3, chunk=size)
    engine = Engine(spark)
    engine.fit(source, spec, 2 * size, 4 * size, keep=True)
    state = engine.fit(source, spec, size, 5 * size, keep=True).state
    return spark.createDataFrame([(i, round(float(v), 6)) for i, v in enumerate(state.w)], "i int, w double")


@query(_step_sql(3) + " select cast(j as int) as i, round(avg(w[j + 1]), 6) as w, cast(0 as bigint) as jobs, cast(0 as double) as points_read from w3, (select unnest(range(11)) as j) where c >= 2 and c < 4 group by j")
def logit_covered_request(spark, sf_dir):
    """A request that kept chunks cover: the answer, without a job or a point read."""
    from spanfold.engine import Engine

    source = lineitem_source(spark, sf_dir)
    size = size_of(source) // CHUNKS
    spec = replace(ONE_STEP, steps=3, chunk=size)
    engine = Engine(spark)
    engine.fit(source, spec, 2 * size, 4 * size, keep=True)
    before = source.stats["jobs"]
    answer = engine.fit(source, spec, 2 * size, 4 * size)
    return spark.createDataFrame([(i, round(float(v), 6), source.stats["jobs"] - before, float(answer.points_read)) for i, v in enumerate(answer.state.w)], "i int, w double, jobs long, points_read double")


@query(_step_sql(3) + " select cast(j as int) as i, round(avg(w[j + 1]), 6) as w, true as refused from w3, (select unnest(range(11)) as j) where c >= 1 and c < 5 group by j")
def logit_extend(spark, sf_dir):
    """A model carried on to a wider range by new chunks; taking points away is refused."""
    from spanfold.engine import Engine

    source = lineitem_source(spark, sf_dir)
    size = size_of(source) // CHUNKS
    spec = replace(ONE_STEP, steps=3, chunk=size)
    engine = Engine(spark)
    wide = engine.extend(source, engine.fit(source, spec, 2 * size, 4 * size), size, 5 * size)
    try:
        engine.extend(source, wide, 2 * size, 5 * size)
        refused = False
    except logistic.NotSubtractable:
        refused = True
    return spark.createDataFrame([(i, round(float(v), 6), refused) for i, v in enumerate(wide.state.w)], "i int, w double, refused boolean")


@query(f"""
with {LINES}, {SCALED}, r as (select sqrt(max(list_dot_product(x, x))) as r from sc), k as (select r, n, n // 10 as l, 10 as p from r, size)
select round(r, 6) as radius, round(r * sqrt(2) / 0.1 * (1 / sqrt(l) + 1 / sqrt(n)) + 2 * sqrt(2) * r / (0.1 * sqrt(p * l)) * sqrt(ln(1 / 0.05)), 6) as bound from k""")
def logit_distance_bound(spark, sf_dir):
    source = lineitem_source(spark, sf_dir)
    n = size_of(source)
    r = logistic.largest_norm(source.df, LOGIT).first()["radius"]
    return spark.createDataFrame([(round(r, 6), round(logistic.distance_bound(r, 0.1, n // 10, n, 0.05), 6))], "radius double, bound double")


@query("""
with k as (select n // 10 as a, n * 9 // 10 as b, greatest(1, n // 9) as s from (select count(*) as n from events)),
cuts as (select i, a + i * s as lo, case when i = (b - a) // s - 1 then b else a + (i + 1) * s end as hi from (select *, unnest(range((b - a) // s)) as i from k))
select cast(i as int) as seq, lo, hi, count(*) as n, cast(sum(cast(cast(value as decimal(18,2)) * 100 as bigint)) as bigint) as cents from cuts join events on event_id >= lo and event_id < hi group by i, lo, hi""")
def chunk_ranges(spark, sf_dir):
    """Chunks of a ninth of the events over four fifths of them: the short rest joins the last. Each
    with its points and the sum of their values."""
    source = event_source(spark, sf_dir)
    n = size_of(source)
    cells = [(r.lo, r.hi, i) for i, r in enumerate(logistic.make_chunks(n // 10, n * 9 // 10, max(1, n // 9)))]
    rows = in_cells(source.scan_range(cells[0][0], cells[-1][1]), source.key, cells, "seq int")
    return rows.groupBy("seq", F.col("cell_lo").alias("lo"), F.col("cell_hi").alias("hi")).agg(F.count("*").alias("n"), F.sum(Feature("value", "value", 2).integer()).alias("cents"))


MANY_CHUNKS = 100


@query(f"""
with recursive {LINES}, {SCALED}, pts_c as materialized (select pid // (n // {MANY_CHUNKS}) as c, pid % (n // {MANY_CHUNKS}) as t, x, c2 from sc, size where pid < (n // {MANY_CHUNKS}) * {MANY_CHUNKS}),
run(c, t, w) as (select c, cast(0 as bigint), list_transform(range(11), lambda i: 0.0)::double[] from (select distinct c from pts_c)
  union all select run.c, run.t + 1, list_transform(w, lambda v, i: v - 0.5 * (1 / (1 + exp(-list_dot_product(x, w))) - c2) * x[i]) from run join pts_c on pts_c.c = run.c and pts_c.t = run.t)
select c, cast(j as int) as j, round(w[j + 1], 6) as w from run, (select unnest(range(11)) as j) where t = (select n // {MANY_CHUNKS} from size)""")
def logit_sgd_chunks(spark, sf_dir):
    """A hundred chunk models by one pass of single-point steps, chunks side by side."""
    source = lineitem_source(spark, sf_dir)
    size = size_of(source) // MANY_CHUNKS
    trained = logistic.train_chunks(source.df, LOGIT, logistic.make_chunks(0, size * MANY_CHUNKS, size))
    return trained.select((F.col("chunk_lo") / size).cast("long").alias("c"), F.posexplode("w").alias("j", "w")).select("c", "j", F.round("w", 6).alias("w"))


@query(f"""
with recursive {LINES}, {SCALED}, pts_c as materialized (select pid as t, x, c2 from sc, size where pid < n // 60),
run(t, w) as (select cast(0 as bigint), list_transform(range(11), lambda i: 0.0)::double[]
  union all select run.t + 1, list_transform(w, lambda v, i: v - 0.5 * (1 / (1 + exp(-list_dot_product(x, w))) - c2) * x[i]) from run join pts_c on pts_c.t = run.t)
select cast(j as int) as i, round(w[j + 1], 6) as w from run, (select unnest(range(11)) as j) where t = (select n // 60 from size)""")
def logit_sgd_request(spark, sf_dir):
    """The sequential baseline for a request of a sixtieth of the points."""
    source = lineitem_source(spark, sf_dir)
    w = scratch_sgd(source, LOGIT, 0, size_of(source) // 60).w
    return spark.createDataFrame([(i, round(float(v), 6)) for i, v in enumerate(w)], "i int, w double")


@query()
def logit_sgd_scratch(spark, sf_dir):
    """The sequential baseline over the middle third; a numpy loop checks it in tests."""
    source = lineitem_source(spark, sf_dir)
    w = scratch_sgd(source, LOGIT, *thirds(source)).w
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(w)], "i int, w double")


@query(_step_sql(2).replace("pid < (n // 6) * 6", "pid < n // 3").replace("pid // (n // 6)", "0") + " select cast(j as int) as i, round(w[j + 1], 6) as w from w2, (select unnest(range(11)) as j)")
def logit_batch_scratch(spark, sf_dir):
    """Two full-batch steps over the first third: one chunk is the whole request."""
    source = lineitem_source(spark, sf_dir)
    w = scratch_batch(source, ONE_STEP, 0, size_of(source) // 3, 2).w
    return spark.createDataFrame([(i, round(float(v), 6)) for i, v in enumerate(w)], "i int, w double")


_DRAWS = """
tt as (select t, (((t + 1000003) % 2147483648 * 2654435761) % 2147483648)::bigint as h1 from (select unnest(range(2000)) as t)),
th as (select t, ((xor(h1, h1 >> 15) * 2246822519) % 2147483648)::bigint as h2 from tt),
draws as (select t // 500 as c, cast(floor(xor(h2, h2 >> 13) / 2147483648.0::double * n::double) as bigint) as pid from th, size)"""


@query(_step_sql(2).replace(f"ch as (select *, pid // (n // {CHUNKS}) as c from sc, size where pid < (n // {CHUNKS}) * {CHUNKS})", _DRAWS + ", ch as (select sc.*, c from draws join sc using (pid))")
       + " select cast(j as int) as i, round(avg(w[j + 1]), 6) as w from w2, (select unnest(range(11)) as j) group by j")
def logit_subsample_average(spark, sf_dir):
    """Weights averaged over four sub-samples of 500 points drawn independently with replacement."""
    source = lineitem_source(spark, sf_dir)
    m = logistic.average_of_subsamples(source.df, replace(ONE_STEP, steps=2), p=4, m=500, n=size_of(source))
    return spark.createDataFrame([(i, round(float(v), 6)) for i, v in enumerate(m.w)], "i int, w double")


def _rest_sql() -> str:
    """Three steps for each chunk and each class against the others."""
    out = f"with {LINES}, {SCALED}, ch as (select sc.*, c3, k, pid // (n // {CHUNKS}) as c from sc join (select pid, c3 from full_pts) using (pid), size, (select unnest(['high', 'low', 'middle']) as k) where pid < (n // {CHUNKS}) * {CHUNKS}), w0 as (select distinct c, k, list_transform(range(11), lambda x: 0.0)::double[] as w from ch)"
    for t in range(3):
        out += f""",
g{t} as (select ch.c, ch.k, j, avg((1 / (1 + exp(-list_dot_product(x, w))) - case when c3 = ch.k then 1 else 0 end) * x[j + 1]) + 0.02 * max(w[j + 1]) as g, max(w[j + 1]) as v
  from ch join w{t} on ch.c = w{t}.c and ch.k = w{t}.k, (select unnest(range(11)) as j) group by ch.c, ch.k, j),
w{t + 1} as (select c, k, list(v - 0.5 * g order by j) as w from g{t} group by c, k)"""
    return out + " select k as class, cast(j as int) as i, round(avg(w[j + 1]), 6) as w from w3, (select unnest(range(11)) as j) group by k, j"


@query(_rest_sql())
def logit_one_vs_rest(spark, sf_dir):
    """Three planted classes, each against the rest, from one pass over the points."""
    source = lineitem_source(spark, sf_dir)
    models = logistic.one_vs_rest(source.df, replace(ONE_STEP, steps=3, label=CLASS3), GNB_LINES.classes, _chunk_cuts(size_of(source)))
    return spark.createDataFrame([(c, i, round(float(v), 6)) for c, m in sorted(models.items()) for i, v in enumerate(m.w)], "class string, i int, w double")
