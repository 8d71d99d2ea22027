"""digitsort.functions"""
