"""Extension points chosen by name."""

from __future__ import annotations

_FOUND: dict[tuple[str, str], object] = {}


def register(kind: str, name: str):
    """Decorator: a function under (kind, name); kinds are advantage, loss, filter, grader, correction."""

    def keep(fn):
        if (kind, name) in _FOUND:
            raise ValueError(f"{kind} {name} is registered twice")
        _FOUND[kind, name] = fn
        return fn

    return keep


def get(kind: str, name: str):
    try:
        return _FOUND[kind, name]
    except KeyError:
        raise KeyError(f"no {kind} {name}; known: {names(kind)}") from None


def names(kind: str) -> list[str]:
    return sorted(n for k, n in _FOUND if k == kind)


def checked_advantage(name: str, rollouts, **options):
    """Runs a registered estimator and checks that it keeps the rows and adds a column ``adv`` of finite doubles."""
    from pyspark.sql import functions as F

    out = get("advantage", name)(rollouts, **options)
    if dict(out.dtypes).get("adv") != "double":
        raise TypeError(f"{name} must add a double column adv")
    odd = F.col("adv").isNull() | F.isnan("adv") | (F.abs("adv") == float("inf"))
    n, bad = out.agg(F.count("*"), F.count(F.when(odd, 1))).first()
    if n != rollouts.count() or bad:
        raise ValueError(f"{name} changed the rows or made {bad} values that aren't finite")
    return out
