"""Merging two samples into one by a bounded loop of draft, audit and patch."""
