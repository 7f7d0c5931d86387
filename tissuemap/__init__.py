"""Tissue maps from fingerprint signals, as Spark plans."""
