"""The experiment workloads on the given tables."""
