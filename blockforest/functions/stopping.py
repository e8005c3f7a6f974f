"""Rules that stop a vote early, as integer thresholds: the fewest leader votes that end it after n votes.

Every rule but the Bayesian one has a closed form, so a table of thresholds is one projection over 1..m, and the
stop test is an integer comparison in Python and SQL alike.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction
from functools import lru_cache
from statistics import NormalDist

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rules by name: (kind, sides, finite-population correction).
RULES = {
    "g1_fpc": ("normal", 1, True), "g1": ("normal", 1, False), "g2_fpc": ("normal", 2, True), "g2": ("normal", 2, False),
    "chebyshev": ("chebyshev", 1, False), "chernoff": ("chernoff", 1, False), "certain": ("certain", 1, False), "full": ("full", 1, False), "bayes": ("bayes", 1, False),
}


def check_alpha(alpha: float) -> float:
    if not 0 < alpha < 1:
        raise ValueError(f"alpha must lie in (0, 1), not {alpha}")
    return alpha


def critical_value(alpha: float, sides: int) -> float:
    return NormalDist().inv_cdf(1 - check_alpha(alpha) / sides)


def min_votes(alpha: float) -> int:
    """Votes before a Gaussian rule may stop; between the stated levels the stricter one holds."""
    return 15 if alpha >= 1e-2 else 30 if alpha >= 1e-3 else 45


def correction(n, m: int):
    """Finite-population correction of the half-width: 1 up to a twentieth of the members."""
    n = np.asarray(n, float)
    return np.where(n > 0.05 * m, np.sqrt(np.maximum(m - n, 0) / max(m - 1, 1)), 1.0)


@dataclass(frozen=True)
class Rule:
    """A stopping rule for ensembles of m members at disagreement level alpha."""

    name: str = "g1_fpc"
    m: int = 100
    alpha: float = 0.01
    min_votes: int | None = None
    #: How the Bayesian rule judges over two classes: leader against runner-up, by enumeration, or by sampling.
    multi: str = "pairwise"

    def __post_init__(self):
        if self.multi not in ("pairwise", "exact", "sampled"):
            raise ValueError(f"unknown way with several classes {self.multi}")
        if self.name not in RULES:
            raise ValueError(f"unknown rule {self.name}")
        if self.m < 1:
            raise ValueError("an ensemble has at least one member")
        check_alpha(self.alpha)

    @property
    def least(self) -> int:
        kind = RULES[self.name][0]
        return self.min_votes if self.min_votes is not None else min_votes(self.alpha) if kind == "normal" else 1

    def square(self) -> float:
        """z squared, or what stands for it."""
        kind, sides, _ = RULES[self.name]
        return critical_value(self.alpha, sides) ** 2 if kind == "normal" else 1 / self.alpha

    def leads(self) -> np.ndarray:
        """Entry n: fewest leader votes that stop after n votes (m+1 where none can); entry 0 is unused."""
        m, kind = self.m, RULES[self.name][0]
        n = np.arange(m + 1, dtype=float)
        never = m + 1
        if kind == "bayes":
            out = bayes_leads(m, self.alpha)
        elif kind == "full":
            out = np.full(m + 1, never)
        elif kind == "certain":
            out = np.full(m + 1, m // 2 + 1)
        else:
            n[0] = 1
            if kind == "chernoff":
                share = 0.5 + np.sqrt(math.log(1 / self.alpha) / (2 * n))
            else:
                rho = correction(n, m) if RULES[self.name][2] else 1.0
                c = self.square() * rho**2 / n
                share = 0.5 + 0.5 * np.sqrt(c / (1 + c))
            out = np.floor(n * share).astype(np.int64) + 1
        out = np.where(np.arange(m + 1) < self.least, never, out)
        return np.where(out > np.arange(m + 1), never, out)

    def longest_by_leader(self) -> np.ndarray:
        """The table by the leader's votes instead: entry k is the most votes cast at which k leader votes still stop.

        The minimum of votes is left out (it is tested beside the table). Where the finite-population correction
        switches on, a leader may fail at n and pass at n + 1: this form then stops at the smaller n too.
        """
        from dataclasses import replace

        leads = replace(self, min_votes=1).leads()
        out = np.zeros(self.m + 1, np.int64)
        n = np.arange(1, self.m + 1)
        real = leads[1:] <= n
        np.maximum.at(out, leads[1:][real], n[real])
        return np.maximum.accumulate(out)

    def stops(self, lead: int, n: int) -> bool:
        return bool(lead >= _leads(self)[n])

    def stops_multi(self, top: np.ndarray, second: np.ndarray, n: int) -> np.ndarray:
        """Leader against runner-up, other classes left out; corrections and minimum votes count all n votes."""
        kind, _, fpc = RULES[self.name]
        pair = top + second
        if n < self.least or kind == "full":
            return np.zeros(len(top), bool)
        if kind == "certain":
            return top > second + (self.m - n)
        if kind == "bayes":
            return pairwise_bayes(top, second, n, self.m, self.alpha)
        rho = float(correction(n, self.m)) if fpc else 1.0
        if kind == "chernoff":
            share = 0.5 + np.sqrt(math.log(1 / self.alpha) / (2 * pair))
        else:
            c = self.square() * rho**2 / pair
            share = 0.5 + 0.5 * np.sqrt(c / (1 + c))
        return top >= np.floor(pair * share) + 1


    def stops_tallies(self, tallies: np.ndarray, n: int) -> np.ndarray:
        """Do the rows of a table of votes by class stop after n votes?"""
        if RULES[self.name][0] == "bayes" and self.multi != "pairwise":
            ask = bayes_multi_exact if self.multi == "exact" else bayes_multi_sampled
            states, row = np.unique(np.sort(tallies, axis=1), axis=0, return_inverse=True)
            return np.array([n >= self.least and max(ask(s.tolist(), self.m)) >= 1 - self.alpha for s in states])[row.ravel()]
        two = np.partition(tallies, -2, axis=1)[:, -2:]
        return self.stops_multi(two[:, 1], two[:, 0], n)


@lru_cache(64)
def _leads(rule: Rule) -> np.ndarray:
    return rule.leads()


#: One table for each rule, kept.
threshold_table = _leads


# -- Bayesian rule --------------------------------------------------------------------------------------


@lru_cache(8)
def _log_factorials(n: int) -> np.ndarray:
    return np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, n + 1)))])


def bayes_final_prob(lead: int, n: int, m: int) -> float:
    """Probability that the leader ends with over half of m votes, uniform prior: a beta-binomial tail in log space."""
    rest, other = m - n, n - lead
    need = m // 2 + 1 - lead
    if need <= 0:
        return 1.0
    if need > rest:
        return 0.0
    lf = _log_factorials(2 * m + 2)
    k = np.arange(need, rest + 1)
    log_p = lf[rest] - lf[k] - lf[rest - k] + lf[lead + k] + lf[other + rest - k] - lf[n + rest + 1] + lf[n + 1] - lf[lead] - lf[other]
    return float(min(1.0, np.exp(log_p).sum()))


def bayes_final_prob_exact(lead: int, n: int, m: int) -> Fraction:
    """The same with big integers."""
    rest, other = m - n, n - lead
    total = sum(math.comb(lead + k, k) * math.comb(other + rest - k, rest - k) for k in range(max(0, m // 2 + 1 - lead), rest + 1))
    return Fraction(total, math.comb(n + 1 + rest, rest))


def _prime_exponents(n: int) -> np.ndarray:
    """Row k: exponents of the primes up to n in k factorial."""
    primes = [p for p in range(2, n + 1) if all(p % q for q in range(2, int(p**0.5) + 1))]
    out = np.zeros((n + 1, len(primes)), np.int64)
    for j, p in enumerate(primes):
        q = p
        while q <= n:
            out[q::q, j] += 1
            q *= p
    return np.cumsum(out, axis=0), np.array(primes, object)


def bayes_final_prob_primes(lead: int, n: int, m: int) -> float:
    """The same by prime factors of every term: slow, for comparison (m up to 500)."""
    if m > 500:
        raise ValueError("the prime-factor form is for ensembles of at most 500")
    e, primes = _cached_exponents(2 * m + 2)
    rest, other = m - n, n - lead
    total = Fraction(0)
    for k in range(max(0, m // 2 + 1 - lead), rest + 1):
        x = e[lead + k] - e[lead] - e[k] + e[other + rest - k] - e[other] - e[rest - k] - (e[n + 1 + rest] - e[rest] - e[n + 1])
        up, down = (int(np.prod(primes[s > 0] ** s[s > 0].astype(object))) if (s > 0).any() else 1 for s in (x, -x))
        total += Fraction(up, down)
    return float(total)


_cached_exponents = lru_cache(4)(_prime_exponents)


def bayes_leads(m: int, alpha: float, prob=None, allow_slow: bool = False) -> np.ndarray:
    """Fewest leader votes with a winning probability of at least 1 - alpha.

    Without ``prob`` the probabilities come from those of one vote later, n by n: the next vote is the leader's with the
    odds that its votes so far give it. Only leads whose outcome is open (between 1e-17 and 1 - 1e-16) are carried along, about the
    root of m of them, so large tables are in reach. With ``prob`` each probability is computed by itself (log space,
    fractions, prime factors), and a pointer moves by few steps for each n.
    """
    if prob is None:
        return _bayes_leads_backward(m, alpha)
    if m > 20_000 and not allow_slow:
        raise ValueError("a Bayesian table is quadratic in m: pass allow_slow=True above 20,000")
    out = np.full(m + 1, m + 1)
    at = 1
    for n in range(1, m + 1):
        at = max(at, (n + 1) // 2)
        while at <= n and prob(at, n, m) < 1 - alpha:
            at += 1
        while at - 1 >= (n + 1) // 2 and at - 1 <= n and prob(at - 1, n, m) >= 1 - alpha:
            at -= 1
        out[n] = at if at <= n else m + 1
        at = min(at, n)
    return out


def _bayes_leads_backward(m: int, alpha: float) -> np.ndarray:
    out = np.full(m + 1, m + 1)
    # win[i] is the probability at lead low + i; below it is 0, behind it is 1
    low, win = m // 2 + 1, np.zeros(0)
    for n in range(m, 0, -1):
        if n < m:
            lead = np.arange(low - 1, low + len(win))  # from the leads of one vote later
            later = np.concatenate([[0.0], win, [1.0]])
            p = (lead + 1) / (n + 2)
            win, low = later[1:] * p + later[:-1] * (1 - p), low - 1
            keep = (win > 1e-17) & (win < 1 - 1e-16)
            first = int(keep.argmax()) if keep.any() else int((win <= 1e-17).sum())
            stop = len(win) - int(keep[::-1].argmax()) if keep.any() else first
            low, win = low + first, win[first:stop]
        least = max(low + int(np.searchsorted(win, 1 - alpha)), (n + 1) // 2, 1)
        out[n] = least if least <= n else m + 1
    return out


def pairwise_bayes(top: np.ndarray, second: np.ndarray, n: int, m: int, alpha: float) -> np.ndarray:
    """Leader against runner-up as if the votes to come were theirs alone."""
    out = np.zeros(len(top), bool)
    for a, b in {(int(x), int(y)) for x, y in zip(top, second, strict=True)}:
        size = a + b + (m - n)
        out[(top == a) & (second == b)] = bayes_final_prob(a, a + b, size) >= 1 - alpha
    return out


def bayes_multi_exact(tally: list[int], m: int, limit: int = 200_000) -> list[float]:
    """Winning probability of every class by enumeration of the votes to come (ties are nobody's)."""
    c, r = len(tally), m - sum(tally)
    if math.comb(r + c - 1, c - 1) > limit:
        raise ValueError("too many outcomes to enumerate: use the pairwise or sampled form")
    wins = [Fraction(0)] * c
    total = math.comb(sum(tally) + c - 1 + r, r)

    def outcomes(left, k):
        if k == 1:
            yield (left,)
            return
        for x in range(left + 1):
            for rest in outcomes(left - x, k - 1):
                yield (x, *rest)

    for extra in outcomes(r, c):
        final = [t + x for t, x in zip(tally, extra, strict=True)]
        best = max(final)
        if final.count(best) == 1:
            wins[final.index(best)] += math.prod(math.comb(t + x, x) for t, x in zip(tally, extra, strict=True))
    return [float(w / total) for w in wins]


def bayes_multi_sampled(tally: list[int], m: int, draws: int = 4000, seed: int = 0) -> np.ndarray:
    """The same by draws from the posterior."""
    rng = np.random.default_rng(seed)
    p = rng.dirichlet(np.array(tally) + 1, draws)
    final = np.array([rng.multinomial(m - sum(tally), q) for q in p]) + tally
    top = final.max(axis=1)
    alone = (final == top[:, None]).sum(axis=1) == 1
    return np.bincount(final[alone].argmax(axis=1), minlength=len(tally)) / draws


# -- DataFrame forms ------------------------------------------------------------------------------------


def correction_column(n: Column, m: int) -> Column:
    n = n.cast("double")
    return F.when(n > 0.05 * m, F.sqrt((float(m) - n) / float(max(m - 1, 1)))).otherwise(F.lit(1.0))


def table_literal(rule: Rule) -> Column:
    """The table of a rule as one folded literal: entry n (from 1) is the threshold after n votes."""
    return F.split(F.lit(",".join(map(str, _leads(rule)[1:].tolist()))), ",").cast("array<int>")


def lead_column(rule: Rule, n: Column) -> Column:
    """Threshold after n votes as a column expression (null where the vote can't stop)."""
    kind, _, fpc = RULES[rule.name]
    x = n.cast("double")
    if kind == "full":
        lead = F.lit(None).cast("long")
    elif kind == "certain":
        lead = F.lit(rule.m // 2 + 1).cast("long")
    elif kind == "chernoff":
        lead = F.floor(x * (0.5 + F.sqrt(F.lit(math.log(1 / rule.alpha)) / (2.0 * x)))) + 1
    elif kind == "bayes":
        lead = F.element_at(table_literal(rule), n.cast("int")).cast("long")
    else:
        rho = correction_column(n, rule.m) if fpc else F.lit(1.0)
        c = F.lit(rule.square()) * rho * rho / x
        lead = F.floor(x * (0.5 + 0.5 * F.sqrt(c / (1.0 + c)))) + 1
    return F.when((n >= rule.least) & (lead <= n), lead)


def thresholds(spark: SparkSession, rule: Rule) -> DataFrame:
    """``n, min_lead`` for n = 1..m, one projection over a range."""
    n = F.col("id").cast("int")
    return spark.range(1, rule.m + 1).select(n.alias("n"), lead_column(rule, n).alias("min_lead"))


def stored_thresholds(spark: SparkSession, rule: Rule, folder: str) -> DataFrame:
    """``thresholds`` kept as Parquet: built by the first session that asks for them, read by all others."""
    path = f"{folder.rstrip('/')}/{rule.name}_m{rule.m}_a{rule.alpha!r}_v{rule.least}"
    place = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    if not place.getFileSystem(spark._jsc.hadoopConfiguration()).exists(place):
        thresholds(spark, rule).coalesce(1).write.mode("overwrite").parquet(path)
    return spark.read.parquet(path)


def gaussian_stop(lead: Column, n: Column, rule: Rule) -> Column:
    return F.coalesce(lead >= lead_column(rule, n), F.lit(False))


def thresholds_sql(rule: Rule) -> str:
    """``thresholds`` in DuckDB."""
    kind, _, fpc = RULES[rule.name]
    m = rule.m
    rho2 = f"(CASE WHEN n > {0.05 * m!r} THEN ({m}.0 - n) / {max(m - 1, 1)}.0 ELSE 1.0 END)" if fpc else "1.0"
    if kind == "full":
        lead = "NULL::BIGINT"
    elif kind == "certain":
        lead = f"({m // 2 + 1})::BIGINT"
    elif kind == "chernoff":
        lead = f"(floor(n::DOUBLE * (0.5::DOUBLE + sqrt({math.log(1 / rule.alpha)!r}::DOUBLE / (2.0 * n::DOUBLE)))))::BIGINT + 1"
    elif kind == "bayes":
        # beta-binomial tail by lgamma, then the first lead that reaches the level
        return f"""WITH s AS (SELECT n, lead FROM range(1, {m + 1}) t(n), range(1, {m + 1}) u(lead) WHERE lead <= n AND 2 * lead >= n),
        p AS (SELECT n, lead, least(1.0, sum(exp(lgamma({m}-n+1) - lgamma(k+1) - lgamma({m}-n-k+1) + lgamma(lead+k+1) + lgamma({m}-lead-k+1) - lgamma({m}+2) + lgamma(n+2) - lgamma(lead+1) - lgamma(n-lead+1)))) AS p
              FROM s, range(0, {m + 1}) v(k) WHERE k <= {m} - n AND lead + k >= {m // 2 + 1} GROUP BY n, lead)
        SELECT t.n::INTEGER AS n, (SELECT min(lead) FROM p WHERE p.n = t.n AND p.p >= {1 - rule.alpha!r}::DOUBLE)::BIGINT AS min_lead FROM range(1, {m + 1}) t(n)"""
    else:
        c = f"({rule.square()!r}::DOUBLE * {rho2}::DOUBLE / n::DOUBLE)"
        lead = f"(floor(n::DOUBLE * (0.5::DOUBLE + 0.5::DOUBLE * sqrt({c} / (1.0::DOUBLE + {c})))))::BIGINT + 1"
    return f"SELECT n::INTEGER AS n, CASE WHEN n >= {rule.least} AND lead <= n THEN lead END AS min_lead FROM (SELECT n, {lead} AS lead FROM range(1, {m + 1}) t(n))"
