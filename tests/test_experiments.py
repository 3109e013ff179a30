"""The experiments run the same methods on graphs of every size."""

from pushwave.plans import experiments as X

SLOW = {("ablation", m) for m in ("halving", "halving indexed", "bounds", "bounds indexed")} | {("top-k", m) for m in ("monte carlo", "filter-refine", "hub-indexed")}


def test_top_k_leaves_no_method_out_on_a_larger_graph(spark, monkeypatch):
    asked, sizes = [], []
    monkeypatch.setattr(X.Bench, "top", lambda self, workload, method, *_: (asked.append((workload, method)), sizes.append(self.g.n), 1.0)[2])
    monkeypatch.setattr(X.B, "tune_push_only", lambda *_, **__: (0.1, None))
    X.top_k(spark, "/root/testdata/sf0.001", ("emb_knn",), ks=(5,), count=1)
    assert min(sizes) > 300 and set(asked) >= SLOW
