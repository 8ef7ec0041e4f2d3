"""Direction rules, cost measures, ablations and experiment workloads."""
