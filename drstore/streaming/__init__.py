"""Appended documents and request streams."""
