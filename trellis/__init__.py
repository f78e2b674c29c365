"""trellis: conjunctive graph-pattern queries on Spark, with workload-adaptive placement."""
