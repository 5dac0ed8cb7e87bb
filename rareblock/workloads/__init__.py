"""The experiment workloads on the given tables, as queries and as SQL of equal output."""
