"""The experiment workloads on the given tables, with the SQL that checks them."""
