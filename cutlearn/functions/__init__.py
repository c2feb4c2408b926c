"""cutlearn.functions"""
