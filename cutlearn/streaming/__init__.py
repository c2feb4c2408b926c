"""cutlearn.streaming"""
