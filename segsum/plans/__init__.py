"""Specifications, the experiment workloads, and the SQL surface."""
