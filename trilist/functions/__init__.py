"""trilist.functions"""
