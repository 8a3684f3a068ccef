"""Whole methods put together, experiment workloads, the query registry and plan inspection."""
