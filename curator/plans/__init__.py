"""End-to-end plans: the curator, its ablations, the baselines, and the experiment workloads."""
