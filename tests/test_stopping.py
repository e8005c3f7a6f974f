import itertools

import numpy as np
import pytest

from blockforest.functions import stopping as st

#: rule, m, alpha, {n: fewest leader votes; None: can't stop}
GOLDEN = [
    ("g1_fpc", 100, 0.01, {15: 12, 20: 15, 30: 21, 50: 31, 75: 43, 90: 49, 99: 51, 100: 51}),
    ("g1", 100, 0.01, {15: 12, 30: 21, 50: 33, 75: 48, 90: 56, 99: 61, 100: 62}),
    ("g2_fpc", 100, 0.01, {15: 12, 30: 21, 50: 32, 75: 44, 90: 49, 99: 51}),
    ("g2", 100, 0.01, {15: 12, 30: 22, 50: 34, 75: 49, 90: 57, 99: 62, 100: 63}),
    ("bayes", 100, 0.01, {5: None, 7: 7, 8: 8, 10: 9, 15: 12, 20: 15, 30: 21, 50: 32, 75: 43, 90: 49, 99: 51}),
    ("g1_fpc", 1000, 0.01, {15: 12, 50: 33, 100: 61, 500: 269, 1000: 501}),
    ("g1_fpc", 10000, 0.01, {15: 12, 100: 62, 500: 276, 501: 276, 5000: 2559, 10000: 5001}),
    ("g1_fpc", 10000, 1e-4, {45: 34, 100: 68, 500: 292, 501: 291, 5000: 2593}),
    ("bayes", 1000, 0.01, {7: 7, 15: 13, 50: 34, 100: 62, 500: 269}),
    ("bayes", 1000, 1e-4, {10: None, 14: 14, 45: 35, 100: 68}),
]


@pytest.mark.parametrize("name,m,alpha,want", GOLDEN)
def test_golden(name, m, alpha, want):
    leads = st.threshold_table(st.Rule(name, m, alpha))
    for n, lead in want.items():
        assert leads[n] == (m + 1 if lead is None else lead)


def test_closed_form_is_the_interval_test():
    for name, m, alpha in itertools.product(("g1_fpc", "g1", "g2_fpc", "g2"), (1, 2, 37, 100, 400), (0.05, 0.01, 1e-3)):
        rule = st.Rule(name, m, alpha, min_votes=1)
        z, leads = st.critical_value(alpha, st.RULES[name][1]), rule.leads()
        for n in range(1, m + 1):
            rho = float(st.correction(n, m)) if st.RULES[name][2] else 1.0
            ok = [k for k in range(n // 2, n + 1) if 2 * k > n and k / n - rho * z * np.sqrt(k / n * (1 - k / n) / n) > 0.5 + 1e-12]
            assert leads[n] == (ok[0] if ok else m + 1), (name, m, alpha, n)


def test_bayes_forms_agree():
    for m in (1, 2, 9, 24, 60):
        for n in range(1, m + 1, 3):
            for lead in range((n + 1) // 2, n + 1):
                exact = float(st.bayes_final_prob_exact(lead, n, m))
                assert abs(st.bayes_final_prob(lead, n, m) - exact) < 1e-10
                assert abs(st.bayes_final_prob_primes(lead, n, m) - exact) < 1e-12
    two = st.bayes_multi_exact([5, 2], 15)
    assert abs(two[0] - float(st.bayes_final_prob_exact(5, 7, 15))) < 1e-12
    three = st.bayes_multi_exact([4, 2, 1], 14)
    assert np.abs(np.array(three) - st.bayes_multi_sampled([4, 2, 1], 14, 20000)).max() < 0.02
    with pytest.raises(ValueError):
        st.bayes_multi_exact([1, 1, 1, 1, 1], 500)


def test_table_by_leader():
    for name, m in (("g1", 200), ("g2", 77)):  # exact where no correction switches on
        rule = st.Rule(name, m, 0.01, min_votes=1)
        leads, longest = rule.leads(), rule.longest_by_leader()
        assert all((n <= longest[k]) == (leads[n] <= k) for n in range(1, m + 1) for k in range(1, n + 1) if leads[n] <= n)
    rule = st.Rule("g1_fpc", 10_000, 1e-4)
    assert rule.longest_by_leader()[291] >= 501 and rule.leads()[500] == 292  # the known exception


def test_orders_and_limits():
    for m in (50, 300):
        t = {n: st.Rule(n, m, 0.01).leads() for n in ("g1_fpc", "g1", "g2", "g2_fpc")}
        assert (t["g1_fpc"] <= t["g1"]).all() and (t["g1"] <= t["g2"]).all() and (t["g2_fpc"] <= t["g2"]).all()
        for x in t.values():
            n = np.arange(m + 1)
            real = x <= n
            assert (2 * x[real] > n[real]).all()
    assert st.Rule("full", 5).leads()[1:].min() == 6 and st.Rule("certain", 5).leads()[3] == 3
    assert [st.min_votes(a) for a in (0.05, 0.01, 5e-3, 1e-3, 1e-4)] == [15, 15, 30, 30, 45]
    for bad in (0, 1, -0.1):
        with pytest.raises(ValueError):
            st.Rule("g1", 10, bad)
    with pytest.raises(ValueError):
        st.bayes_leads(30_000, 0.01, st.bayes_final_prob)


def test_bayes_tables_from_vote_to_vote_equal_log_space():
    from blockforest.functions.stopping import bayes_final_prob, bayes_leads

    for m in (1, 2, 3, 10, 51, 200, 1000):
        for alpha in (0.05, 0.01, 1e-4):
            assert (bayes_leads(m, alpha) == bayes_leads(m, alpha, bayes_final_prob)).all()
    assert bayes_leads(30_000, 0.01)[1000] > 500
