"""Settings of a score, and the text that names one with all its parameters."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

VERSION = 1
METRICS = ("ttr", "moment", "zipf")
NONLINEARITIES = ("pow", "entropy", "sq_entropy")
DISTANCES = ("sq", "log", "sq_log", "jsd", "kl_pq", "kl_qp", "abs")
LENGTH_MODES = ("clamp", "hyperbolic", "exponential")
NORMS = ("ratio", "difference", "none")
SUPPORTS = ("observed", "bounded")
EPS_ON = ("count", "prob")


@dataclass(frozen=True)
class Setting:
    """One score: what is counted, how the distribution is smoothed and cut, the metric, and how length is made up for."""

    metric: str = "moment"
    unit: str = "char"
    n: int = 6
    lam: float = 0.0
    eps: float = 0.0
    eps_on: str = "count"
    top_k: int | None = None
    g: str = "pow"
    k: float = 2.0
    d: str = "sq"
    exponent: float = 1.0
    shift: float = 0.0
    support: str = "observed"
    asymptote: float = 2000.0
    mode: str = "clamp"
    norm: str = "ratio"
    cap: int | None = None

    def __post_init__(self):
        for value, known in ((self.metric, METRICS), (self.g, NONLINEARITIES), (self.d, DISTANCES), (self.mode, LENGTH_MODES), (self.norm, NORMS), (self.support, SUPPORTS), (self.eps_on, EPS_ON)):
            if value not in known:
                raise ValueError(f"{value!r} is none of {known}")
        if self.n < 1 or self.lam < 0 or self.eps < 0 or self.asymptote <= 0 or (self.top_k is not None and self.top_k < 1):
            raise ValueError("n and top_k must be at least 1, lam and eps at least 0, asymptote above 0")

    @property
    def spec(self) -> tuple[str, int]:
        return self.unit, self.n

    def but(self, **changes) -> Setting:
        return replace(self, **changes)


@dataclass(frozen=True)
class Ensemble:
    """The mean of several scores of one metric: of more n-gram lengths, or of characters and words."""

    members: tuple[Setting, ...]

    def __post_init__(self):
        if len({m.metric for m in self.members}) != 1 or len({m.cap for m in self.members}) != 1:
            raise ValueError("an ensemble needs members of one metric, over texts of one cap")

    @property
    def metric(self) -> str:
        return self.members[0].metric

    @property
    def cap(self) -> int | None:
        return self.members[0].cap

    def but(self, **changes) -> Ensemble:
        return Ensemble(tuple(m.but(**changes) for m in self.members))


def members(s: Setting | Ensemble) -> tuple[Setting, ...]:
    return s.members if isinstance(s, Ensemble) else (s,)


def _text(x) -> str:
    if x is None or x == math.inf:
        return "inf"
    return repr(int(x)) if float(x) == int(x) else repr(float(x))


def signature(s: Setting | Ensemble) -> str:
    """Text with every parameter that the metric uses, in a fixed order; of an ensemble, its members' in brackets."""
    if isinstance(s, Ensemble):
        return "mean(" + ";".join(map(signature, s.members)) + ")"
    parts = [s.metric, f"u={s.unit}", f"n={s.n}", f"lam={_text(s.lam)}", f"eps={_text(s.eps)}@{s.eps_on}", f"k={_text(s.top_k)}"]
    if s.metric != "ttr":
        parts.append(f"g={s.g}{_text(s.k) if s.g == 'pow' else ''}" if s.metric == "moment" else f"d={s.d}")
        if s.metric == "zipf":
            parts.append(f"q=power:{_text(s.exponent)}:{_text(s.shift)}:{s.support}")
        parts.append(f"A={_text(s.asymptote)}:{s.mode}:{s.norm}")
    return "|".join([*parts, f"cap={_text(s.cap)}", f"v={VERSION}"])


def _number(t: str) -> float:
    return math.inf if t == "inf" else float(t)


def parse_signature(text: str) -> Setting | Ensemble:
    """The setting that a signature names. An unknown or missing field is an error."""
    if text.startswith("mean(") and text.endswith(")"):
        return Ensemble(tuple(map(parse_signature, text[5:-1].split(";"))))
    metric, *rest = text.split("|")
    got: dict = {"metric": metric}
    pairs = [p.partition("=")[::2] for p in rest]
    for key, value in pairs:
        if key == "u":
            got["unit"] = value
        elif key == "n":
            got["n"] = int(value)
        elif key == "lam":
            got["lam"] = float(value)
        elif key == "eps":
            number, _, got["eps_on"] = value.partition("@")
            got["eps"] = float(number)
        elif key == "k":
            got["top_k"] = None if value == "inf" else int(value)
        elif key == "g":
            name = next((g for g in sorted(NONLINEARITIES, key=len, reverse=True) if value.startswith(g)), value)
            got["g"] = name
            if name == "pow":
                got["k"] = float(value[3:])
        elif key == "d":
            got["d"] = value
        elif key == "q":
            kind, exponent, shift, got["support"] = value.split(":")
            if kind != "power":
                raise ValueError(f"unknown rank model {kind!r}")
            got["exponent"], got["shift"] = float(exponent), float(shift)
        elif key == "A":
            number, got["mode"], got["norm"] = value.split(":")
            got["asymptote"] = _number(number)
        elif key == "cap":
            got["cap"] = None if value == "inf" else int(value)
        elif key == "v":
            if value != str(VERSION):
                raise ValueError(f"version {value} is not {VERSION}")
        else:
            raise ValueError(f"unknown field {key!r}")
    setting = Setting(**got)
    if signature(setting) != text:
        raise ValueError(f"{text!r} is not a complete signature; that would be {signature(setting)!r}")
    return setting
