"""cutlearn.sources"""
