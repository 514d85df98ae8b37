from lakejoin.operators import chain
from lakejoin.plans import context


def test_registered_chain_uses_the_selected_settings(monkeypatch):
    used = []
    monkeypatch.setattr(chain, "fit_chain", lambda labelled, params=chain.SMALL, chained=True: used.append((params, chained)))
    monkeypatch.setattr(context.Context, "train", None)
    c = context.Context(None, "")
    _ = c.model, c.unchained
    assert used == [(chain.BEST, True), (chain.BEST, False)]
