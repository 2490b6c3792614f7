"""The experiment workloads, restated on the given tables."""
