"""The experiment workloads on the given tables, and SQL for the same questions."""
