"""The experiment workloads on the given tables: programs, their inputs, and reference SQL written by hand."""
