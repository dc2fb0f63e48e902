"""The results tables as lists of configurations, scaled to the given tables."""

from __future__ import annotations

from dataclasses import replace

from carepath.plans.experiments import Config, Scale


def _rows(prefix: str, features: list[str], **settings) -> list[Config]:
    return [Config(f"{prefix}: {f}", features=f, **settings) for f in features]


def initial_tuned(scale: Scale = Scale()) -> list[Config]:
    """Five folds of visits balanced once, encoder tuned on all rows: leaky on purpose."""
    return _rows("initial tuned", ["text", "stay", "gap", "gap+stay", "gap+stay+text"], folds="visit5", balance="once", encoder="tuned_all", scale=scale)


def initial_frozen(scale: Scale = Scale()) -> list[Config]:
    return _rows("initial frozen", ["text", "stay", "gap", "gap+text", "gap+stay", "gap+stay+text"], folds="visit", scale=scale)


def final_return(scale: Scale = Scale()) -> list[Config]:
    return [*_rows("return", ["text", "stay", "gap", "text+stay", "gap+text", "gap+stay", "gap+stay+text"], scale=scale), Config("return: gap+stay+text+dx_c", features="gap+stay+text+dx", level="parent", scale=scale)]


def next_codes(level: str, scale: Scale = Scale()) -> list[Config]:
    sets = ["text", "dx", "text+dx", "dx+gap", "text+dx+med", "text+dx+proc", "text+dx+gap", "text+dx+gap+proc", "text+dx+gap+proc+med"]
    return _rows(f"codes {level}", sets, task="codes", level=level, balance=None, scale=scale)


#: Cell, hidden (V for the class number, W for the fused width), layers, both directions, window.
VECTOR_ROWS = (("lstm", "V", 1, False, 3), ("lstm", "V", 1, True, 3), ("lstm", "W", 1, True, 3), ("lstm", "W", 1, True, 6), ("lstm", "V", 2, True, 3), ("lstm", "W", 2, True, 3), ("lstm", "W", 2, True, 6), ("lstm", "W", 3, True, 3), ("gru", "W", 2, True, 3))
MULTI_HOT_ROWS = (("gru", "V", 1, False, 3), ("gru", "V", 1, True, 3), ("gru", "V", 1, True, 6), ("gru", "V", 2, True, 3), ("gru", "V", 2, True, 6), ("lstm", "V", 1, True, 3), ("lstm", "V", 1, True, 6))


def _sequence(rows, source: str, scale: Scale, classes: int) -> list[Config]:
    width = {"V": classes, "W": scale.d + scale.temporal_width}
    return [Config(f"sequence {source}: {cell} {h} x{n}{' both' if both else ''} k={k}", task="codes", features="dx+gap", balance=None, cell=cell, hidden=width[h], layers=n, bidirectional=both, window=k, source=source, scale=scale) for cell, h, n, both, k in rows]


def on_vectors(scale: Scale = Scale(), classes: int = 25) -> list[Config]:
    return _sequence(VECTOR_ROWS, "vector", scale, classes)


def on_multi_hot(scale: Scale = Scale(), classes: int = 25) -> list[Config]:
    return _sequence(MULTI_HOT_ROWS, "multi_hot", scale, classes)


def text_return_comparator(scale: Scale = Scale()) -> Config:
    return Config("text return comparator", features="text", folds="visit5", balance="once", encoder="tuned_train", scale=scale)


def text_code_comparator(scale: Scale = Scale()) -> Config:
    return Config("text code comparator", task="codes", features="text", target="current", balance=None, folds="labels", scale=scale)


def sequence_comparator(scale: Scale = Scale(), level: str = "grp") -> Config:
    return Config(f"sequence comparator: {level}", task="codes", level=level, features="dx", balance=None, cell="minimal_gru", hidden=27, bidirectional=True, source="multi_hot", samples="prefixes", head="softmax", folds="holdout", scale=scale)


def return_on_sequences(scale: Scale = Scale()) -> list[Config]:
    return [Config(f"return sequence k={k}", features="gap+stay", balance=None, cell="gru", hidden=25, window=k, scale=scale) for k in (3, 6)]


def future_targets(scale: Scale = Scale()) -> list[Config]:
    codes = {"task": "codes", "balance": None, "scale": scale}
    return [
        Config("next procedures", features="dx+gap", target_kind="P", **codes), Config("next medications", features="dx+gap", target_kind="M", **codes),
        Config("pooled notes in sequences", features="text+dx+gap", cell="gru", **codes),
        Config("multi-hot by concept vectors in sequences", features="dx", cell="gru", source="concepts", **codes),
    ]


def same_targets(scale: Scale = Scale(), k: int = 3) -> list[Config]:
    """The single visit first; then sequences of k visits whose samples have the same target visits."""
    codes = {"task": "codes", "features": "dx+gap", "balance": None, "scale": scale}
    return [Config("single visit", targets_of=k, **codes), Config("sequence of vectors", cell="gru", window=k, bidirectional=True, **codes), Config("sequence of codes", cell="gru", window=k, bidirectional=True, source="multi_hot", **codes)]


def grid(base: Config, **options) -> list[Config]:
    """Every combination of the given options of a configuration."""
    out = [base]
    for key, values in options.items():
        out = [replace(c, **{key: v, "name": f"{c.name} {key}={v}"}) for c in out for v in values]
    return out
