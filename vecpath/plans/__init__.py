"""Choice of the access path: workload, rules, cost model and published measurements."""
