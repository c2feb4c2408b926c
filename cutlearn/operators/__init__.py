"""cutlearn.operators"""
