"""The code behind the registry's entries: (executor, parameters, inputs) to a value."""

from __future__ import annotations

from collections.abc import Callable

from ..operators import encoders, models, profile


def prep_expressions(ex, p: dict, df, states: dict):
    return encoders.apply_all(df, p["prep"]["encoders"], states, p["prep"]["carry"], p["train"])


def prep_rows(ex, p: dict, df, states: dict):
    return encoders.apply_rows(df, p["prep"]["encoders"], states, p["prep"]["carry"], p["train"])


def moments(kernel: str) -> Callable:
    def run(ex, p: dict, data) -> dict:
        return models.moments(encoders.filtered(data.df, p["rows"]), data.features, p["target"], p["by"], kernel)

    return run


def solve_moments(ex, p: dict, data, sums: dict) -> dict:
    m = sum(v for k, v in sums.items() if p["leave_out"] is None or k != p["leave_out"])
    model = p["model"]
    return models.solve_ridge(m, model["alpha"]) if model["kind"] == "ridge" else models.solve_elastic_net(m, model["alpha"], model["rho"])


def solve_mllib(ex, p: dict, data, sums: dict) -> dict:
    """The JVM library's solver over the training rows; the sums aren't looked at."""
    model = p["model"]
    rows = data.df.filter(p["rows"]) if p.get("rows") else data.df
    return models.mllib_linear(rows, data.features, p["target"], model["alpha"], model.get("rho"))


def tree_options(p: dict) -> dict:
    return {k: v for k, v in p["model"].items() if k != "kind"}


def boosted(ex, p: dict, data, told: dict) -> dict:
    rows = encoders.filtered(data.df, p["train"])
    return models.boost(rows, data.features, p["target"], **told, shared=ex.binned(data, rows, p["train"], p["target"], told.get("bins", 16)))


def trees_histograms(ex, p: dict, data) -> dict:
    return boosted(ex, p, data, tree_options(p))


def trees_few(ex, p: dict, data) -> dict:
    """Low fidelity: half the trees on half the bins."""
    told = tree_options(p)
    told |= {"trees": max(1, told.get("trees", 8) // 2), "bins": max(4, told.get("bins", 16) // 2)}
    return boosted(ex, p, data, told)


def trees_mllib(ex, p: dict, data) -> dict:
    return models.mllib_boost(data.df.filter(p["train"]), data.features, p["target"], **tree_options(p))


def classifier_logistic(ex, p: dict, data) -> dict:
    return models.logistic(data.df.filter(p["train"]), data.features, p["target"], p["model"].get("alpha", 1e-3))


def classifier_perceptron(ex, p: dict, data) -> dict:
    return models.perceptron(data.df.filter(p["train"]), data.features, p["target"], hidden=p["model"].get("hidden", 4), epochs=p["model"].get("epochs", 50))


def svd(method: str) -> Callable:
    def run(ex, p: dict, df):
        return models.truncated_svd(df, p["column"], p["k"], method, p.get("size"))

    return run


def distinct(exact: bool) -> Callable:
    def run(ex, p: dict, df):
        return profile.profile_cardinality(df, p["columns"], exact)

    return run
