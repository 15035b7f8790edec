"""Query plans: the experiment workloads and operators as queries over the given tables."""
