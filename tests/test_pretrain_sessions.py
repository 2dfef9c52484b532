"""Every session of a client takes part in pre-training."""

import numpy as np

from fedlake.plans import pretrain


class Watch:
    """An encoder that notes what it is asked to tell apart."""

    def __init__(self):
        self.targets, self.negatives = [], []

    def item_mask(self, phi, view, target, negatives):
        self.targets.append(target)
        self.negatives.append(negatives)
        return 1.0, np.zeros_like(phi)


def test_all_sessions_and_the_whole_catalogue(monkeypatch):
    monkeypatch.setattr(pretrain, "_bags", lambda seq: [x["item_no"] for x in seq])
    item = lambda k: {"item_no": k, "f": [0], "s": [k]}
    sessions = [{"session_id": k, "seq": [item(3 * k + j) for j in range(3)]} for k in range(300)]
    watch = Watch()
    pretrain.ssl_gradient(watch, np.zeros(2), sessions, 1.0, 0.0, np.random.default_rng(0), [item(k) for k in range(900)])
    assert [t[0] // 3 for t in watch.targets] == list(range(300))
    assert all(t[0] not in n for t, n in zip(watch.targets, watch.negatives, strict=True))
    assert len({x for n in watch.negatives for x in n}) > 700


def test_long_sessions_lose_no_item(spark, folder):
    from pyspark.sql import functions as F

    from fedlake.operators import sequences as S
    from fedlake.plans import data as D
    from fedlake.sources import universes as U

    prep, gap = D.prepare(U.universe(spark, folder, "E")), 1000 * 24 * 3600  # one session per client
    rows = U.event_rows(spark, folder)
    known = rows.join(prep.items.select("item_id"), "item_id", "left_semi")
    expected = S.sessions(known, gap, S.MIN_VIEW).agg(F.sum("n"), F.max("n")).first()
    sizes = [len(w["seq"]) for r in pretrain.client_sequences(prep, rows, gap, "event_id").collect() for w in r.sessions]
    assert expected[1] > pretrain.LONGEST
    assert sum(sizes) == expected[0] and max(sizes) <= pretrain.LONGEST and min(sizes) >= S.MIN_VIEW
