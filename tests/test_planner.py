from vpatterns.plans.planner import choose


def test_choices():
    assert choose(10**6, 12, 90, 4).merge == "sequential"
    assert choose(10**6, 40, 90, 4).merge == "tree"
    wide = choose(10**12, 2113, 96, 8)
    assert (wide.workflow, wide.clustering, wide.merge) == ("wide", "driver", "membership")
    assert choose(10**6, 10**5, 99.9, 8).clustering == "distributed"
    assert choose(10**6, 500, 10, 8, 3).similarity == "gram"
