"""Networks of the experiment workloads on the given tables."""
