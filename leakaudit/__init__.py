"""Membership-inference auditing of language models, written as Spark plans."""
