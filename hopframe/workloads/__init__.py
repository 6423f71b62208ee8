"""The experiment workloads on the given tables: query texts, and the SQL each is held against."""
