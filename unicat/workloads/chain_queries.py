"""Queries of the samplers' kernels: one step on fixed states, with DuckDB twins."""

from __future__ import annotations

import re
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import graph, posterior, sampler
from ..params import Params
from ..registry import query
from ..rng import u01_sql
from . import text_queries as q


# One step on the fixed state

PICK = q.ON + f""",
picked AS (SELECT arg_min(cp, ({u01_sql("42", "0", "'p'", "cp")}, cp)) AS cp FROM (SELECT DISTINCT cp FROM cps)),
cats AS (SELECT list_sort(list(DISTINCT cat)) AS cats FROM labels_now),
move AS (SELECT p.cp, min(l.cat) AS cat_from, len(any_value(cats))::BIGINT AS k,
  coalesce(any_value(cats)[1 + floor({u01_sql("42", "0", "'l'", "p.cp")} * (len(any_value(cats)) + 1))::INT], list_max(any_value(cats)) + 1) AS cat_to
  FROM picked p JOIN cps USING (cp) JOIN labels_now l USING (item_id), cats GROUP BY p.cp)"""

ACROSS = """,
across AS (SELECT x.cp AS cp_s, y.cp AS cp_t, a.cat AS cat_s, b.cat AS cat_t, q FROM edges JOIN cps x ON x.item_id = s JOIN cps y ON y.item_id = t
  JOIN labels_now a ON a.item_id = s JOIN labels_now b ON b.item_id = t WHERE x.cp <> y.cp),
cross_ends AS (SELECT cp_s AS cp, cat_t AS other, q FROM across UNION ALL SELECT cp_t, cat_s, q FROM across)"""

RATIO = ACROSS + """,
ratio AS (SELECT m.cp, coalesce(sum(CASE WHEN cat_from = cat_to THEN 0 WHEN other = cat_to THEN ln(1 - q) WHEN other = cat_from THEN -ln(1 - q) ELSE 0 END), 0) AS log_ratio
  FROM move m LEFT JOIN cross_ends USING (cp) GROUP BY m.cp)"""


def move_of(spark, sf_dir) -> DataFrame:
    parts, labels = q.parts(spark, sf_dir), q.languages(spark, sf_dir)
    return sampler.propose_label(sampler.pick_component(parts, 42, 0), parts, labels, 42, 0)


@query("i02_cut_components", q.ON + " SELECT cp, count(*) AS n FROM cps GROUP BY cp")
def i02(spark, sf_dir):
    return q.parts(spark, sf_dir).groupBy("cp").agg(F.count(F.lit(1)).alias("n"))


@query("i03_pick", PICK + " SELECT cp FROM picked")
def i03(spark, sf_dir):
    return sampler.pick_component(q.parts(spark, sf_dir), 42, 0)


@query("i04_proposal", PICK + " SELECT cp, cat_from, cat_to, k FROM move")
def i04(spark, sf_dir):
    return move_of(spark, sf_dir)


@query("i05_cut_ratio", PICK + RATIO + " SELECT cp, round(log_ratio, 6) AS log_ratio FROM ratio")
def i05(spark, sf_dir):
    return q.rounded(sampler.log_cut_ratio(q.edges(spark, sf_dir), q.parts(spark, sf_dir), q.languages(spark, sf_dir), move_of(spark, sf_dir)), "log_ratio")


UPPER = q.ON + ACROSS + """,
upper_g AS (SELECT least(cp_s, cp_t) AS a, greatest(cp_s, cp_t) AS b, 1 - exp(sum(ln(1 - q))) AS q FROM across WHERE cat_s = cat_t GROUP BY 1, 2)"""
COMP = UPPER + f""",
c_on AS (SELECT a, b FROM upper_g WHERE {u01_sql("42", "0", "'c'", "a", "b")} < q),
c_duo AS (SELECT a AS u, b AS v FROM c_on UNION ALL SELECT b, a FROM c_on),
c_reach(cp, spot) AS (SELECT DISTINCT cp, cp FROM cps UNION SELECT r.cp, d.v FROM c_reach r JOIN c_duo d ON r.spot = d.u),
comps AS (SELECT cp, min(spot) AS comp FROM c_reach GROUP BY cp),
c_pick AS (SELECT comp FROM (SELECT comp, u, min(u) OVER () AS low FROM (SELECT comp, {u01_sql("42", "0", "'k'", "comp")} AS u FROM (SELECT DISTINCT comp FROM comps))) WHERE u < 0.3 OR u = low)"""


def upper(spark, sf_dir) -> DataFrame:
    return q.held(spark, sf_dir, "upper", lambda: sampler.component_graph(q.edges(spark, sf_dir), q.parts(spark, sf_dir), q.languages(spark, sf_dir)))


def comps(spark, sf_dir) -> DataFrame:
    return q.held(spark, sf_dir, "comps", lambda: sampler.composites(upper(spark, sf_dir), q.parts(spark, sf_dir), 42, 0))


@query("i08_cp_graph", UPPER + " SELECT a, b, round(q, 6) AS q FROM upper_g")
def i08(spark, sf_dir):
    return q.rounded(upper(spark, sf_dir), "q")


@query("i09_composites", COMP + " SELECT cp, comp FROM comps")
def i09(spark, sf_dir):
    return comps(spark, sf_dir)


@query("i10_picked_composites", COMP + " SELECT comp FROM c_pick")
def i10(spark, sf_dir):
    return sampler.pick_composites(comps(spark, sf_dir), 42, 0)


@query(
    "i12_cut_ratio2",
    COMP
    + f""",
c_cats AS (SELECT list_sort(list(DISTINCT cat)) AS cats FROM labels_now),
of_item AS (SELECT item_id, comp, cat FROM cps JOIN comps USING (cp) JOIN labels_now USING (item_id)),
c_move AS (SELECT comp, min(cat) AS cat_from, coalesce(any_value(cats)[1 + floor({u01_sql("42", "0", "'l'", "comp")} * (len(any_value(cats)) + 1))::INT], list_max(any_value(cats)) + 1) AS cat_to
  FROM of_item JOIN c_pick USING (comp), c_cats GROUP BY comp),
c_across AS (SELECT x.comp AS c_s, y.comp AS c_t, x.cat AS cat_s, y.cat AS cat_t, q FROM edges JOIN of_item x ON x.item_id = s JOIN of_item y ON y.item_id = t WHERE x.comp <> y.comp),
c_ends AS (SELECT c_s AS comp, cat_t AS other, q FROM c_across UNION ALL SELECT c_t, cat_s, q FROM c_across)
SELECT m.comp, cat_from, cat_to, round(2 * coalesce(sum(CASE WHEN cat_from = cat_to THEN 0 WHEN other = cat_to THEN ln(1 - q) WHEN other = cat_from THEN -ln(1 - q) ELSE 0 END), 0), 6) AS log_ratio
FROM c_move m LEFT JOIN c_ends USING (comp) GROUP BY m.comp, cat_from, cat_to""",
)
def i12(spark, sf_dir):
    """Both levels of cuts of every picked composite: within one label the second equals the first."""
    labels = q.languages(spark, sf_dir)
    atoms = q.parts(spark, sf_dir).join(comps(spark, sf_dir), "cp").select("item_id", F.col("comp").alias("cp"))
    picked = sampler.pick_composites(comps(spark, sf_dir), 42, 0).withColumnRenamed("comp", "cp")
    moves = sampler.propose_label(picked, atoms, labels, 42, 0)
    ratio = sampler.log_cut_ratio(q.edges(spark, sf_dir), atoms, labels, moves)
    return moves.join(ratio, "cp").select(F.col("cp").alias("comp"), "cat_from", "cat_to", F.round(2 * F.col("log_ratio"), 6).alias("log_ratio"))


def _after(sql: str) -> str:
    """The model CTEs for the labels after the move."""
    for name in ("sizes", "means", "ref", "lambdas", "gains", "models", "labels_now"):
        sql = sql.replace(f"{name} AS (", f"{name}_b AS (").replace(f"FROM {name} ", f"FROM {name}_b ").replace(f"JOIN {name} ", f"JOIN {name}_b ").replace(f"FROM {name})", f"FROM {name}_b)").replace(f"SELECT {name}.*", f"SELECT {name}_b.*")
    return sql


STEP = (
    PICK
    + RATIO
    + ","
    + posterior.model_sql(q.N_SQL, q.TYPES)
    + ", labels_now_b AS (SELECT item_id, CASE WHEN cps.cp = move.cp THEN cat_to ELSE cat END AS cat FROM labels_now JOIN cps USING (item_id), move),"
    + _after(posterior.model_sql(q.N_SQL, q.TYPES))
    + """,
e_a AS (SELECT count(*) AS k, 300.0 * count(*) - sum(ll) AS e FROM (SELECT n * sum(gain) AS ll FROM models GROUP BY cat, n)),
e_b AS (SELECT count(*) AS k, 300.0 * count(*) - sum(ll) AS e FROM (SELECT n * sum(gain) AS ll FROM models_b GROUP BY cat, n)),
alpha AS (SELECT least(0, log_ratio + ln((e_a.k + 1.0) / (e_b.k + 1.0)) + e_a.e - e_b.e) AS la FROM ratio, e_a, e_b)
"""
)


@query(
    "i16_single_step",
    STEP
    + f"""SELECT move.cp, cat_from, cat_to, e_a.k AS k_before, e_b.k AS k_after, round(e_a.e, 5) AS energy_before, round(e_b.e, 5) AS energy_after, round(la, 5) AS log_alpha,
  ln({u01_sql("42", "0", "'a'")}) < la AS accepted FROM move, e_a, e_b, alpha""",
)
def i16(spark, sf_dir):
    resp, labels = q.responses(spark, sf_dir), q.languages(spark, sf_dir)
    reference = posterior.reference_means(resp, labels.count(), q.TYPES)
    report, _ = sampler.single_step(resp, q.edges(spark, sf_dir), labels, reference, Params(), 0)
    return report.select("cp", "cat_from", "cat_to", "k_before", "k_after", *[F.round(c, 5).alias(c) for c in ("energy_before", "energy_after", "log_alpha")], "accepted")


@query("p11_delta_energy", STEP + "SELECT e_a.k AS k_before, e_b.k AS k_after, round(e_b.e - e_a.e, 5) AS delta FROM e_a, e_b")
def p11(spark, sf_dir):
    """The energy difference of the move from the two touched categories alone."""
    resp, labels, move = q.responses(spark, sf_dir), q.languages(spark, sf_dir), move_of(spark, sf_dir)
    reference = posterior.reference_means(resp, labels.count(), q.TYPES)
    touched = move.select(F.explode(F.array("cat_from", "cat_to")).alias("cat")).distinct()
    after = sampler.moved_labels(labels, q.parts(spark, sf_dir), move)

    def part(state, name):
        own = state.join(F.broadcast(touched), "cat", "left_semi")
        m = posterior.select_words(posterior.category_means(resp, own), reference)
        return posterior.energy(m, 300.0).select(F.col("k").alias(f"k_{name}"), F.coalesce("energy", F.lit(0.0)).alias(f"e_{name}"))

    rest = labels.join(F.broadcast(touched), "cat", "left_anti").agg(F.countDistinct("cat").alias("k_rest"))
    d = part(labels, "a").crossJoin(part(after, "b")).crossJoin(rest)
    return d.select((F.col("k_a") + F.col("k_rest")).alias("k_before"), (F.col("k_b") + F.col("k_rest")).alias("k_after"), F.round(F.col("e_b") - F.col("e_a"), 5).alias("delta"))


# The same kernels on a second state: a greater tau, so that not every edge is on, and the keyed guess as labels, so that
# edges of one label cross components and a move can change the number of categories.
SEED2, TAU2 = 61, 2.0
ON2 = q.TEXT + "," + graph.graph_sql(q.DIMS, tau=TAU2) + "," + "labels_now AS (SELECT item_id, cat FROM (" + q.GUESS_SQL + " SELECT item_id, cat FROM assigned))," + q.ON.split(q.LABELS_SQL + ",")[1]


def _second(sql: str) -> str:
    """The SQL of a kernel on the second state, with its seed."""
    return ON2 + sql[len(q.ON) :]


def _seeded(sql: str) -> str:
    return sql.replace("(42)::VARCHAR", f"({SEED2})::VARCHAR")


def labels2(spark, sf_dir) -> DataFrame:
    return q.guess(spark, sf_dir).select("item_id", "cat")


def edges2(spark, sf_dir) -> DataFrame:
    return q.held(spark, sf_dir, "edges2", lambda: q.near(spark, sf_dir, tau=TAU2))


def parts2(spark, sf_dir) -> DataFrame:
    return q.held(spark, sf_dir, "parts2", lambda: graph.components(graph.draw_edges(edges2(spark, sf_dir), labels2(spark, sf_dir), SEED2, 0), labels2(spark, sf_dir)))


def upper2(spark, sf_dir) -> DataFrame:
    return q.held(spark, sf_dir, "upper2", lambda: sampler.component_graph(edges2(spark, sf_dir), parts2(spark, sf_dir), labels2(spark, sf_dir)))


def comps2(spark, sf_dir) -> DataFrame:
    return q.held(spark, sf_dir, "comps2", lambda: sampler.composites(upper2(spark, sf_dir), parts2(spark, sf_dir), SEED2, 0))


def atoms2(spark, sf_dir) -> DataFrame:
    return parts2(spark, sf_dir).join(comps2(spark, sf_dir), "cp").select("item_id", F.col("comp").alias("cp"))


@query("i05_cut_ratios_of_all", _seeded(_second(q.ON + ACROSS)) + """,
to_all AS (SELECT cp, cat FROM (SELECT DISTINCT cp FROM cps), (SELECT DISTINCT cat FROM labels_now)),
from_of AS (SELECT cp, min(cat) AS cat_from FROM cps JOIN labels_now USING (item_id) GROUP BY cp),
both_sums AS (SELECT cp, other, sum(ln(1 - q)) AS w FROM cross_ends GROUP BY ALL)
SELECT t.cp, t.cat AS cat_to, round(coalesce(n.w, 0) - coalesce(o.w, 0), 6) AS log_ratio FROM to_all t JOIN from_of f USING (cp)
  LEFT JOIN both_sums n ON n.cp = t.cp AND n.other = t.cat LEFT JOIN both_sums o ON o.cp = t.cp AND o.other = f.cat_from WHERE t.cat <> f.cat_from""")
def i05_all(spark, sf_dir):
    """The cut ratio of moving each component to each other label."""
    parts, labels, out = parts2(spark, sf_dir), labels2(spark, sf_dir), None
    old = parts.join(labels, "item_id").groupBy("cp").agg(F.min("cat").alias("cat_from"))
    for cat in sorted(r.cat for r in labels.select("cat").distinct().collect()):
        moves = old.where(F.col("cat_from") != cat).withColumn("cat_to", F.lit(cat).cast("long"))
        r = sampler.log_cut_ratio(edges2(spark, sf_dir), parts, labels, moves).select("cp", F.lit(cat).cast("long").alias("cat_to"), F.round("log_ratio", 6).alias("log_ratio"))
        out = r if out is None else out.unionByName(r)
    return out


@query("i08_cp_graph_second", _seeded(_second(UPPER)) + " SELECT a, b, round(q, 6) AS q FROM upper_g")
def i08_second(spark, sf_dir):
    return q.rounded(upper2(spark, sf_dir), "q")


@query("i09_composites_second", _seeded(_second(COMP)) + " SELECT cp, comp FROM comps")
def i09_second(spark, sf_dir):
    return comps2(spark, sf_dir)


@query("i10_picked_second", _seeded(_second(COMP)) + " SELECT comp FROM c_pick")
def i10_second(spark, sf_dir):
    return sampler.pick_composites(comps2(spark, sf_dir), SEED2, 0)


REPORT = f"""SELECT move.cp, cat_from, cat_to, e_a.k AS k_before, e_b.k AS k_after, round(log_ratio, 6) AS log_ratio, round(e_a.e, 4) AS energy_before, round(e_b.e, 4) AS energy_after, round(la, 4) AS log_alpha,
  ln({u01_sql(str(SEED2), "0", "'a'")}) < la AS accepted FROM move, e_a, e_b, alpha, ratio"""


def _report(spark, sf_dir, atoms: DataFrame, factor: float) -> DataFrame:
    resp, labels = q.responses(spark, sf_dir), labels2(spark, sf_dir)
    reference = posterior.reference_means(resp, labels.count(), q.TYPES)
    report, _ = sampler.atom_step(resp, edges2(spark, sf_dir), labels, atoms, reference, replace(Params(), seed=SEED2), 0, factor)
    return report.select("cp", "cat_from", "cat_to", "k_before", "k_after", F.round("log_ratio", 6).alias("log_ratio"), *[F.round(c, 4).alias(c) for c in ("energy_before", "energy_after", "log_alpha")], "accepted")


@query("i16_single_step_second", _seeded(_second(STEP)) + REPORT)
def i16_second(spark, sf_dir):
    """A step whose proposal is a new label, so that the ratio of label counts comes in."""
    return _report(spark, sf_dir, parts2(spark, sf_dir), 1.0)


#: From components to composites: the same CTEs over atoms.
_ATOMS = re.sub(r"\bcps\b", "atoms", STEP[len(q.ON) :])
for _name in ("across", "cross_ends"):
    _ATOMS = re.sub(rf"\b{_name}\b", f"{_name}_c", _ATOMS)
_ATOMS = _ATOMS.replace("least(0, log_ratio +", "least(0, 2 * log_ratio +")


@query("i16_composite_step", _seeded(_second(COMP)) + ", atoms AS (SELECT item_id, comp AS cp FROM cps JOIN comps USING (cp))" + _seeded(_ATOMS) + REPORT.replace("round(log_ratio, 6)", "round(2 * log_ratio, 6)"))
def i16_composite(spark, sf_dir):
    """One composite moved, with both levels of cuts."""
    return _report(spark, sf_dir, atoms2(spark, sf_dir), 2.0)
