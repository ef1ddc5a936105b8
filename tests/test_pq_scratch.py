from lowrank_spark.plans import experiments
from lowrank_spark.runtime import Scratch


def test_pairs_of_a_setting_do_not_stay(spark, monkeypatch):
    """Candidate pairs of one p and q are deleted before those of the next are written; only the exact neighbours stay."""
    here, keep, drop = {}, Scratch.keep, Scratch.drop
    most = []

    def kept(self, df, by=None):
        out = keep(self, df, by)
        if self.base.rsplit("/", 1)[-1].startswith("lowrank-x5-"):
            here[out._scratch_path] = True
            most.append(len(here))
        return out

    def dropped(self, df):
        here.pop(df._scratch_path, None)
        drop(self, df)

    monkeypatch.setattr(Scratch, "keep", kept)
    monkeypatch.setattr(Scratch, "drop", dropped)
    rows = experiments.x5_pq(spark, "/root/testdata/sf0.001", ps=(1, 2), qs=(2, 3)).collect()
    assert [(r.p, r.q) for r in rows] == [(1, 2), (1, 3), (2, 2), (2, 3)] and all(r.pairs > 0 for r in rows[:2])
    assert max(most) == 3 and len(here) == 1
