"""Tables of the method: special codes, gates, screening rules, commands."""

from __future__ import annotations

from dataclasses import dataclass, field

#: Numbers commonly used as missing-value codes.
SENTINELS = (9999, 9998, 999, 99, 98, -9999, -9998, -999, -998, -99, -9, -8, -7, -1)


@dataclass(frozen=True)
class Gates:
    """Thresholds of a classifier; None switches a gate off."""

    version: str = "census-1"
    support_cap: int = 25
    strip: bool = True
    core_low: float = -90
    core_high: float = 90
    binary_distinct: int = 2
    ordinal_max: float = 12
    ordinal_distinct: int = 12
    count_skew: float | None = 1.0
    count_distinct: int | None = 4
    count_max: float | None = 1e6
    unit_distinct: int | None = 12
    heavy_skew: float = 2.0
    sentinels: tuple = field(default=SENTINELS)


CENSUS = Gates()
#: Earlier stages of the classifier: with the sentinel step and the count gates
#: but any share in the unit interval a proportion; and without those, too.
HARDENED = Gates(version="hardened-1", unit_distinct=None)
PILOT = Gates(
    version="pilot-1", strip=False, count_skew=None, count_distinct=None, count_max=None, unit_distinct=None
)
#: A raw profiler of its own thresholds (unpublished ones are parameters here).
RAW = Gates(version="raw-1", strip=False, ordinal_max=10, ordinal_distinct=10, count_skew=0.5, unit_distinct=None)

SCALE_LEVEL = {
    "count": "ratio",
    "binary": "nominal",
    "ordinal": "ordinal",
    "proportion": "ratio",
    "heavy-tailed": "ratio",
    "categorical": "nominal",
    "continuous": "continuous",
}

#: (family, class, tier, stratum): what a screen flags.
SCREEN_RULES = [
    ("linear", "count", "clear", "count under linear"),
    ("linear", "proportion", "clear", "share under linear"),
    ("linear", "binary", "debated", "linear probability model"),
    ("linear", "ordinal", "debated", "ordinal as continuous"),
]

#: Another version of the screen: the clear tier alone.
CLEAR_RULES = [r for r in SCREEN_RULES if r[2] == "clear"]

#: (language, command, family, refit): commands the extractor knows.
COMMANDS = [
    ("stata", "regress", "linear", True),
    ("stata", "reg", "linear", True),
    ("stata", "xtreg", "linear", False),
    ("stata", "areg", "linear", False),
    ("stata", "reghdfe", "linear", False),
    ("stata", "ivregress", "linear", False),
    ("stata", "ivreg2", "linear", False),
    ("stata", "mixed", "linear", False),
    ("stata", "anova", "linear", False),
    ("stata", "poisson", "count", False),
    ("stata", "nbreg", "count", False),
    ("stata", "zinb", "count", False),
    ("stata", "zip", "count", False),
    ("stata", "logit", "binary", False),
    ("stata", "logistic", "binary", False),
    ("stata", "probit", "binary", False),
    ("stata", "ologit", "ordinal", False),
    ("stata", "oprobit", "ordinal", False),
    ("stata", "betareg", "proportion", False),
    ("stata", "fracreg", "proportion", False),
    ("stata", "ttest", "t-test", False),
    ("r", "lm", "linear", True),
    ("r", "lm_robust", "linear", True),
    ("r", "lm.cluster", "linear", True),
    ("r", "felm", "linear", False),
    ("r", "feols", "linear", False),
    ("r", "lmer", "linear", False),
    ("r", "aov", "linear", False),
    ("r", "glm", "by family", False),
    ("r", "glm.nb", "count", False),
    ("r", "zeroinfl", "count", False),
    ("r", "polr", "ordinal", False),
    ("r", "betareg", "proportion", False),
    ("r", "t.test", "t-test", False),
]

#: Commands that are another command's short form.
SHORT_FORMS = {"reg": "regress", "ivreg2": "ivregress", "logistic": "logit"}

#: Families of R's glm by its family argument; a missing one is Gaussian.
GLM_FAMILIES = {
    "gaussian": "linear",
    "poisson": "count",
    "quasipoisson": "count",
    "negbin": "count",
    "binomial": "binary",
    "quasibinomial": "proportion",
}

#: Prefixes that a Stata command may carry; the survey prefix is left out.
PREFIXES = ("xi", "bysort", "by", "quietly", "qui", "capture", "cap", "noisily", "noi", "eststo", "bootstrap", "robust")
