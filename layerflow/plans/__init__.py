"""Multi-step inference plans, baselines and workloads."""
