"""The experiment workloads on the given tables: inputs, queries and their SQL twins."""
