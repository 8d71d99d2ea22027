"""digitsort.plans"""
