from privsurv.llm.packing import plan


def test_lengths_that_fit_exactly_share_sequences():
    placed, made = plan({2050: 100, 2046: 100}, 4096)
    assert made == 100 and sum(x[2] for x in placed) == 200
