"""Distributed publish/subscribe over a stream of located texts, on Spark."""
