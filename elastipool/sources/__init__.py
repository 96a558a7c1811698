"""Readers of labelled data and of request traffic."""
