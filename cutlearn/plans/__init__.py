"""cutlearn.plans"""
