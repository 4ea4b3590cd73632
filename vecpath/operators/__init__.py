"""Physical operators: exhaustive scans, graph probes, relational probes and vector joins."""
