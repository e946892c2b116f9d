"""Whole methods: the clustering loop and its parts in order."""
