"""The audit's methods: contracts, probes, verdicts, traces, replay, mutation and measures."""
