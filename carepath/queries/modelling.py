"""Queries that train and score models: rows only, as training is beyond SQL. Each runs a scaled preset of a results table."""

from __future__ import annotations

from dataclasses import replace

from carepath.plans import experiments as X
from carepath.plans import presets as P
from carepath.queries._registry import query
from carepath.queries.visits import _CHUNKS

SCALE = X.Scale(d=16, epochs=2)


@query("m_visit_model_scores")
def _(s, d):
    cfg = X.Config("gap+stay", scale=SCALE)
    return X.visit_models(X.Prepared(s, d), cfg).scores.drop("rotation")


def _sequence_query(name, cell):
    @query(name)
    def _(s, d):
        cfg = X.Config(name, task="codes", features="dx+gap", balance=None, cell=cell, source="multi_hot", scale=SCALE)
        return X.sequence_models(X.Prepared(s, d), cfg).scores.drop("rotation")


_sequence_query("m_gru_scores", "gru")
_sequence_query("m_lstm_scores", "lstm")


#: The rows of each results table, with every rotation.
TABLES: dict[str, list[X.Config]] = {}


def _table(name, configs):
    TABLES[name] = X.in_full(configs)

    @query(name)
    def _(s, d):
        return X.run_all(s, d, TABLES[name])


_table("m_trajectory_eval", P.on_vectors(SCALE))
_table("b_trc", [P.text_return_comparator(SCALE)])
_table("b_tmc", [P.text_code_comparator(SCALE)])
_table("b_seqc", [P.sequence_comparator(SCALE)])
_table("w_tab_i_tuned", P.initial_tuned(SCALE))
_table("w_tab_i_frozen", P.initial_frozen(SCALE))
_table("w_tab_r", P.final_return(SCALE))
_table("w_tab_d", P.next_codes("parent", SCALE))
_table("w_tab_c", P.next_codes("grp", SCALE))
_table("w_tab_s", P.on_vectors(SCALE))
_table("w_tab_m", P.on_multi_hot(SCALE))
_table("w_return_sequences", P.return_on_sequences(SCALE))
_table("w_future_targets", P.future_targets(SCALE))
_table("w_seqc_parent", [P.sequence_comparator(SCALE, "parent")])


@query("w_baseline_compare")
def _(s, d):
    """Single visits, windows of visit vectors and windows of multi-hot codes on the same targets."""
    return X.compared(s, d, X.in_full(P.same_targets(SCALE)))


@query("w_width_sweep")
def _(s, d):
    return X.width_sweep(s, d, scale=replace(SCALE, rotations=tuple(range(10))))


@query("w_precompute", f"WITH {_CHUNKS}, n AS (SELECT count(*) AS c FROM c) SELECT 'stored' AS how, c AS encoder_passes FROM n UNION ALL SELECT 'recomputed', c * 100 FROM n")
def _(s, d):
    return X.cost_report(s, d, 100)
